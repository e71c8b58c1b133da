"""DuckDB SQL of the experiments' reports.

The adaptive spaces need eigenvectors, which SQL does not give; they come from numpy over the file of ``ORACLE_DIR``'s scale (the scale that oracles are run at), and all
else is SQL. Signs of eigenvectors are free: distances do not depend on them.
"""

from __future__ import annotations

import hashlib
import os
import re
from functools import cache

import numpy as np

from ..params import Params, preset
from ..plans import workloads as w
from .pipeline import Pipeline

MODULUS = {"embeddings": 25, "skewed": 25, "doc_vectors": 100}


def _hashed_words(text: str, d: int) -> np.ndarray:
    out = np.zeros(d)
    for word in re.split(r"[ \t\n\x0B\f\r]+", text.lower()):
        if word:
            h = int(hashlib.md5(word.encode()).hexdigest()[:7], 16)
            out[h % d] += 1 if h // d % 2 == 0 else -1
    return out / (np.sqrt((out * out).sum()) or 1)


@cache
def spectrum(path: str, table: str, d: int):
    """Mean, falling eigenvalues and eigenvectors of a vector table's base rows, by numpy from the file alone; None without the file."""
    file = f"{path}/{'documents' if table == 'doc_vectors' else 'embeddings'}.parquet"
    if not os.path.exists(file):
        return None
    import pyarrow.parquet as pq

    rows = pq.read_table(file)
    if table == "doc_vectors":
        x, ids = np.array([_hashed_words(t or "", d) for t in rows.column("text").to_pylist()]), np.array(rows.column("doc_id").to_pylist())
        x, ids = x[np.abs(x).sum(axis=1) > 0], ids[np.abs(x).sum(axis=1) > 0]
    else:
        x, ids = np.array(rows.column("embedding").to_pylist(), float), np.array(rows.column("vec_id").to_pylist())
        x = x * np.arange(1, d + 1) ** -0.7 if table == "skewed" else x
    x = x[ids % MODULUS[table] != 0]
    values, vectors = np.linalg.eigh(np.cov(x, rowvar=False))
    return x.mean(axis=0), values[::-1], vectors[:, ::-1]


def dealt(values: np.ndarray, ns: int, s: int) -> list[list[int]]:
    """The deal, by sums of logarithms and a plain search for the smallest."""
    values = np.maximum(values, 1e-12 * values[0])
    logs, blocks = np.log(values / values[-1]), [[] for _ in range(ns)]
    for r in range(ns * s):
        blocks[min((b for b in range(ns) if len(blocks[b]) < s), key=lambda b: (sum(logs[i] for i in blocks[b]), b))].append(r)
    return blocks


def pipeline(path: str, table: str, space: str, ns: int, s: int, d: int = 64, **options) -> Pipeline:
    if space == "agnostic":
        return Pipeline(table=table, modulus=MODULUS[table], d=d, ns=ns, **options)
    mean, values, vectors = spectrum(path, table, d)
    return Pipeline(table=table, modulus=MODULUS[table], d=d, ns=ns, s=s, directions=[vectors[:, b] for b in dealt(values, ns, s)], mean=mean, **options)


def _of(path: str, table: str, p: Params, d: int = 64) -> Pipeline:
    return pipeline(path, table, p.space, p.ns, p.s, d, l=p.side, t=p.t, alpha=p.alpha, beta=p.beta, k=p.k)


def _row(built: Pipeline, p: Params, **first) -> str:
    """The facts of one setting."""
    if p.selector == "cutoff":
        candidates = "(SELECT round(avg(candidate_num), 4) FROM scores_lookahead) AS candidates, (SELECT max(candidate_num)::BIGINT FROM scores_lookahead) AS most_candidates"
    else:
        budget = f"(SELECT greatest(1, CAST(floor({p.beta} * n) AS BIGINT)) FROM size)"
        candidates = f"{budget}::DOUBLE AS candidates, {budget} AS most_candidates"
    scores = "exact_scores" if p.activation == "exact" else "scores"
    return built.facts(f"{scores}_{'cut' if p.selector == 'cutoff' else 'fixed'}_knn", candidates, **first)


def _all(parts: list[str]) -> str:
    return "\nUNION ALL\n".join(f"SELECT * FROM ({part})" for part in parts)


def _facts(path: str, named: list[tuple[dict, Params]], table: str = "skewed", d: int = 64) -> str:
    groups: dict[tuple, list[tuple[dict, Params]]] = {}
    for first, p in named:
        # settings of one space and alpha share the statement up to the scores
        groups.setdefault((p.space, p.ns, p.s if p.space == "adaptive" else 0, p.cells, p.alpha, p.k, p.activation == "exact"), []).append((first, p))
    parts = []
    for same in groups.values():
        built, rows, more = _of(path, table, same[0][1], d), [], {}
        for b, beta in enumerate(dict.fromkeys(p.beta for _, p in same)):
            own = dict(_of(path, table, same[0][1].to(beta=beta), d).steps)
            more |= {f"{n}_b{b}": _numbered(body, b) for n, body in own.items() if _BY_BETA.fullmatch(n)}
            rows += [_numbered(_row(built, p, **first), b) for first, p in same if p.beta == beta]
        parts.append(built.sql("\nUNION ALL\n".join(rows), **more))
    return _all(parts)


#: The steps that beta has a part in.
_BY_BETA = re.compile(r"(exact_)?scores_(lookahead|fixed_knn|cut_knn|fixed|cut)")


def _numbered(text: str, b: int) -> str:
    return re.sub(rf"\b{_BY_BETA.pattern}\b", lambda m: f"{m.group()}_b{b}", text)


PROFILE = """SELECT {name!r} AS "table", {ns}::BIGINT AS ns, {alpha}::DOUBLE AS alpha, percentile, round(avg(coalesce(score, 0)), 6) AS mean_score
  FROM (SELECT *, ntile(100) OVER (PARTITION BY qid ORDER BY dist, vec_id) AS percentile FROM distances) LEFT JOIN exact_scores USING (qid, vec_id) GROUP BY percentile"""


def _activation(path: str) -> str:
    """Cells in order of their sums until enough points are in: alike for both ways."""
    parts = []
    for cells in w.GRID:
        for alpha in w.STUDY_ALPHAS:
            built = pipeline(path, "embeddings", "agnostic", 2, 4, l=int(cells**0.5), t=3, alpha=alpha)
            each = built.sql("SELECT qid, j, count(*) AS popped, sum((cnt = 0)::INT) AS empty, sum(cnt) AS got FROM activated GROUP BY ALL")
            parts.append(f"SELECT {cells}::BIGINT AS cells, {alpha}::DOUBLE AS alpha, way, round(avg(popped), 4) AS popped, round(avg(empty), 4) AS empty, round(avg(got), 4) AS retrieved, true AS same_cells FROM ({each}), (VALUES ('heap'), ('linear')) v(way) GROUP BY way")
    return _all(parts)


def _best_choice(path: str, recalls: str) -> str:
    """Each method's number of subspaces with the largest recall, the fewest of a tie."""
    return f"SELECT method, ns FROM ({recalls}) QUALIFY row_number() OVER (PARTITION BY method ORDER BY recall DESC, ns) = 1"


def _indexing(path: str) -> str:
    named = [({"method": m, "ns": n}, preset(m, **(w.BASE | {"ns": n}))) for m in w.INDEXED for n in w.CHOICES if not (preset(m).space == "adaptive" and n * w.BASE["s"] > 64)]
    l, s, adaptive = int(w.BASE["cells"] ** 0.5), w.BASE["s"], ", ".join(f"'{m}'" for m in w.INDEXED if preset(m).space == "adaptive")
    width = f"CASE WHEN method IN ({adaptive}) THEN ns * {s} ELSE 64 END"
    model = f"CASE WHEN method IN ({adaptive}) THEN 64 + 64 * ns * {s} ELSE 0 END"
    return f"SELECT method, ns, {width} AS dimensions, 8 * (n * ns + {l} * ({width}) + {model} + ns * {l * l}) AS logical_bytes FROM ({_best_choice(path, _facts(path, named))}), (SELECT count(*) AS n FROM embeddings WHERE vec_id % 25 <> 0)"


def _weighting(path: str) -> str:
    built = _of(path, "skewed", Params(**(w.BASE | {"space": "agnostic"})))
    ns, k, beta = w.BASE["ns"], w.BASE["k"], w.BASE["beta"]
    centres = "SELECT j, list(m ORDER BY pos) AS c FROM (SELECT j, pos, avg(p[pos]) AS m FROM base_parts, range(1, len(p) + 1) r(pos) GROUP BY ALL) GROUP BY j"
    measures = {
        "none": f"SELECT j, 1e0 AS w FROM range(0, {ns}) r(j)",
        "variance": "SELECT j, sum(pow(list_distance(p, c), 2)) / (count(*) - 1) AS w FROM base_parts JOIN centres USING (j) GROUP BY j",
        "mean_distance": "SELECT j, avg(list_distance(p, c)) AS w FROM base_parts JOIN centres USING (j) GROUP BY j",
        "lid": """SELECT j, avg(v) AS w FROM (SELECT a_id, j, -1 / avg(ln(dist / far)) FILTER (rk < 20) AS v, min(dist) AS nearest FROM (
            SELECT *, max(dist) OVER (PARTITION BY a_id, j) AS far FROM (SELECT a.vec_id AS a_id, a.j, list_distance(a.p, b.p) AS dist, row_number() OVER (PARTITION BY a.vec_id, a.j ORDER BY list_distance(a.p, b.p), b.vec_id <> a.vec_id) - 1 AS rk
            FROM base_parts a JOIN base_parts b ON a.j = b.j) WHERE rk BETWEEN 1 AND 20) GROUP BY a_id, j) WHERE nearest > 0 GROUP BY j""",
    }
    given = {}
    for name, body in measures.items():
        given[name] = body
        if name != "none":
            given[f"{name}_inverse"] = f"SELECT j, 1 / (w / (SELECT avg(w) FROM ({body}))) AS w FROM ({body})"
    parts = []
    for name, body in given.items():
        weighed = "SELECT qid, vec_id, round(sum(w / mean), 9) AS score FROM exact JOIN weights USING (j), (SELECT avg(w) AS mean FROM weights) GROUP BY qid, vec_id"
        chosen = f"SELECT * FROM weighed QUALIFY row_number() OVER (PARTITION BY qid ORDER BY score DESC, vec_id) <= (SELECT CAST(floor({beta} * n) AS BIGINT) FROM size)"
        near = f"SELECT c.qid, c.vec_id FROM chosen c JOIN base b USING (vec_id) JOIN queries q ON q.qid = c.qid QUALIFY row_number() OVER (PARTITION BY c.qid ORDER BY list_distance(b.e, q.e), c.vec_id) <= {k}"
        parts.append(built.sql(f"SELECT {name!r} AS weights, round(count(*) / ({k} * (SELECT count(*) FROM queries))::DOUBLE, 4) AS recall FROM near JOIN truth USING (qid, vec_id)", centres=centres, weights=body, weighed=weighed, chosen=chosen, near=near))
    return _all(parts)


def _theory(path: str) -> str:
    ns, parts = w.BASE["ns"], []
    gaps = f"SELECT qid, s_star / (10.0::DOUBLE * {ns}) AS p_star, (s - s_star) / ((n - 10.0::DOUBLE) * {ns}) AS p FROM (SELECT qid, sum(score) FILTER (near) AS s_star, sum(score) AS s FROM (SELECT a.*, t.vec_id IS NOT NULL AS near FROM exact_scores_all a LEFT JOIN truth t USING (qid, vec_id)) GROUP BY qid), size"
    errors = f"SELECT qid, h.s AS threshold, sum((NOT near AND score >= h.s)::INT) / (n - 10.0::DOUBLE) AS type1, sum((near AND score < h.s)::INT) / 10.0::DOUBLE AS type2 FROM (SELECT a.*, t.vec_id IS NOT NULL AS near FROM exact_scores_all a LEFT JOIN truth t USING (qid, vec_id)), range(0, {ns + 2}) h(s), size GROUP BY qid, h.s, n"
    flat = {"base_flat": "SELECT vec_id, flatten(list(p ORDER BY j)) AS p FROM base_parts GROUP BY vec_id", "query_flat": "SELECT qid, flatten(list(p ORDER BY j)) AS p FROM queries_parts GROUP BY qid"}
    pairs = "SELECT q.qid, b.vec_id, pow(list_distance(b.e, q.e), 2) AS whole, pow(list_distance(x.p, y.p), 2) AS kept FROM base b CROSS JOIN queries q JOIN base_flat x ON x.vec_id = b.vec_id JOIN query_flat y ON y.qid = q.qid"
    lost = "SELECT *, CASE WHEN whole > 0 THEN 1 - kept / whole ELSE 0 END AS eps FROM pairs"
    for table in ("embeddings", "skewed"):
        for kind in ("agnostic", "adaptive"):
            p = Params(**(w.BASE | {"space": kind}))
            entropy = 0.0
            if kind == "adaptive":
                values = spectrum(path, table, 64)[1]
                sums = [sum(np.log(values[i]) for i in b) for b in dealt(values, p.ns, p.s)]
                entropy = float(max(sums) - min(sums))
            parts.append(
                _of(path, table, p).sql(
                    f"""SELECT {table!r} AS "table", {kind!r} AS space, round({entropy!r}::DOUBLE, 4) AS entropy_spread, (SELECT round(avg(p_star - p), 4) FROM gaps) AS gap,
                    (SELECT round(avg(exp(-{ns} * (p_star - p) * (p_star - p) / (8 * p * (1 - p)))), 4) FROM gaps) AS bound, (SELECT round(avg(type1), 4) FROM least) AS type1, (SELECT round(avg(type2), 4) FROM least) AS type2,
                    (SELECT round(max(eps), 4) FROM lost) AS worst_loss,
                    (SELECT count(*) FROM lost a JOIN lost b ON a.qid = b.qid AND a.whole < (1 - (SELECT max(eps) FROM lost)) * b.whole AND a.kept > b.kept * (1 + 1e-9)) AS violations""",
                    gaps=gaps, errors=errors, least="SELECT * FROM errors QUALIFY row_number() OVER (PARTITION BY qid ORDER BY type1 + type2, threshold) = 1", **flat, pairs=pairs, lost=lost,
                )
            )
    return _all(parts)


def _cumulative(path: str) -> str:
    p = preset("agnostic+cutoff", **w.BASE)
    built = _of(path, "skewed", p)
    costs = f"SELECT 64e0 * n * {p.side * (p.t + 1)} AS build, 64e0 * ({p.side} + c) AS each, 64e0 * n AS plain FROM size, (SELECT avg(candidate_num) AS c FROM scores_lookahead)"
    caught = "CASE WHEN 0 <= 0 AND build <= 0 THEN 0e0 WHEN each >= plain THEN 'inf'::DOUBLE ELSE ceil(build / (plain - each)) END"
    return built.sql(
        f"""SELECT queries_asked::BIGINT AS queries, method, round(CASE WHEN method = 'exact' THEN queries_asked * plain ELSE build + queries_asked * each END, 4) AS numbers, {caught} AS catches_up_after
        FROM costs, (VALUES (0), (100), (10000)) a(queries_asked), (VALUES ('exact'), ('agnostic+cutoff')) m(method)""",
        costs=costs,
    )


def sql(path: str) -> dict[str, str]:
    """Oracles of the reports; none where the file is not there."""
    if any(spectrum(path, *key) is None for key in (("skewed", 64), ("doc_vectors", 64))):
        return {}
    raw = [
        _of(path, table, Params(space="agnostic", ns=ns, s=2, alpha=alpha)).sql(PROFILE.format(name=table, ns=ns, alpha=alpha)) for table in w.PROFILED for ns, alpha in w.RAW
    ]
    transformed = [_of(path, table, Params(space="adaptive", ns=6, s=8, alpha=0.05)).sql(PROFILE.format(name=table, ns=6, alpha=0.05)) for table in w.PROFILED]
    scan = [({"method": m}, preset(m, **w.SCAN)) for m in ("adaptive", "collision_scan")]
    best = [built.sql(_row(built, p, d=d, ns=ns, s=s, reduction=round(1 - ns * s / d, 4))) for d, ns, s in w.BEST for p in [preset("adaptive", **(w.BASE | {"ns": ns, "s": s, "alpha": 0.05, "beta": 0.05}))] for built in [_of(path, "doc_vectors", p, d)]]
    return {
        "workload_profile_raw": _all(raw), "workload_profile_transformed": _all(transformed), "workload_against_scan": _facts(path, scan, "doc_vectors"),
        "workload_activation_embeddings": _activation(path), "workload_best_settings": _all(best), "workload_indexing": _indexing(path), "workload_weighting": _weighting(path), "workload_theory_checks": _theory(path), "workload_cumulative_work": _cumulative(path),
        "workload_subspace_count": _facts(path, [({"ns": n}, preset("adaptive", **(w.BASE | {"ns": n}))) for n in (2, 4, 6, 8)]),
        "workload_subspace_width": _facts(path, [({"s": s}, preset("adaptive", **(w.BASE | {"s": s}))) for s in (4, 6, 8, 10)]),
        "workload_neighbours_count": _facts(path, [({"method": m, "k": k}, preset(m, **(w.BASE | {"k": k}))) for m in w.INDEXED for k in (1, 10, 20, 50, 100)]),
        "workload_curves": _facts(path, [({"method": m, "alpha": a, "beta": b}, preset(m, **(w.BASE | {"alpha": a, "beta": b}))) for m in w.INDEXED for a in w.ALPHAS for b in w.BETAS]),
    }
