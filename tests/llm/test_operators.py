"""The training-data operators on small tables: brute force, odd rows, empty tables, clashing columns."""

import hashlib
import json
import math
import random
import re
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from annspark.llm import ann, common, decontaminate, language_id, learning, line_dedup, mixing, pii, quality, simhash, tool_calls, url_filter

from .test_small_parts import plain_fingerprint

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
#: Names that operators use inside, and names of the columns that they add.
CLASH = {
    "line": "x", "pos": 1, "fp": 2, "label": 3, "score": 0.5, "item_id": 6, "_id": 7, "_hash": 8, "_copy": 9, "_gone": 10, "_goneh": "y", "_lower": "A b c d e f g", "_lettered": True, "_key": 11, "_own": 12, "_block": 13, "_deal": 14, "_name": "z", "turns": 15, "rest": 16,
    "cut_turn": 17, "site": "s", "least": 18, "mask": 19, "n": 20, "u": "q", "g": "r", "ruled_": 21, "apart": True, "bad": False, "low": 1, "chunk": 2, "bucket": 3, "query_id": 4, "met": 5, "at": 6, "last": 7,
}
ADDED = {"_size": 4, "_source_size": 5, "_target": 6, "_draws": 7, "base": "b", "spans": "c", "lang_pred": "c", "LANG_SCORE": 8, "quality_score": 9, "_lines": 10, "_removed": 11, "host": "h", "rule": "i", "threshold": "j"}


def words(rng, n, stock="the of and to in that it was for on with as by at from this tower river amber stone cloud maple harbor winter signal garden".split()):
    return " ".join(rng.choice(stock) + rng.choice(("", "", "s", "ed")) for _ in range(n))


def table(spark, rows):
    return spark.createDataFrame([(*r, len(r[1]) if r[1] is not None else None) for r in rows], DOCS)


def clashing(df):
    return df.withColumns({k: F.lit(v) for k, v in (CLASH | ADDED).items() if k.lower() not in [c.lower() for c in df.columns]})


def unclashed(df, *added):
    """Every column once, those of CLASH as they came."""
    names = [c.lower() for c in df.columns]
    assert len(set(names)) == len(names) and set(added) <= set(names)
    kept = [c for c in CLASH if c.lower() in names and c not in added]
    rows = df.select(*kept).distinct().collect()
    assert len(rows) == 1 and all(rows[0][k] == CLASH[k] for k in kept)
    return df


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(1, None, "en", "a"), (2, "", "en", None), (3, " \n\t ", None, "a"), (4, "one", "en", "b"), (4, "one", "en", "b"), (None, "some text here", "en", "a"), (5, "word " * 60_000, "en", "b"), (6, "one", "en", "c")]
    return table(spark, rows).repartition(3).cache()


@pytest.fixture(scope="module")
def none(spark):
    return table(spark, [])


# ---- tool calls


def messages(spark, rows):
    return spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")


def call(*calls):
    return json.dumps({"tool_calls": [{"id": i, "name": n, "arguments": a, "depends_on": d} for i, n, a, d in calls]})


def test_tool_calls(spark):
    tools = {"find": {"q": ("string", True), "n": ("integer", False), "o": ("object", False)}}
    rows = [
        (1, 0, "assistant", call(("a", "find", '{"q":"x","n":2}', []), ("b", "find", '{"n":"2","z":1}', ["a"]))),
        (1, 1, "tool", json.dumps({"tool_call_id": "a", "content": "second"})), (1, 2, "tool", json.dumps({"tool_call_id": "a", "content": "later"})),
        (1, 3, "assistant", call(("c", "find", "not json", ["b", "gone"]), ("d", "other", '{"b":1,"a":{"d":1,"c":[2,1]}}', ["d2"]), ("d2", "find", '{"q":null}', ["d"]))),
        (1, 4, "assistant", call(("a", "find", '{"q":"again"}', []))), (2, 0, "assistant", "plain text"), (2, 1, "tool", None), (2, 2, "assistant", ""), (None, 0, "assistant", call(("a", "find", '{"q":"é\\n"}', []))),
    ]
    got = {(r.conv_id, r.id): r for r in tool_calls.link(messages(spark, rows), tools).collect()}
    assert {k: r.level for k, r in got.items()} == {(1, "a"): 0, (1, "b"): 1, (1, "c"): 2, (1, "d"): None, (1, "d2"): None, (None, "a"): 0}
    assert got[1, "a"].n_results == 2 and got[1, "a"].result == "second" and got[1, "a"].problems == [] and got[1, "a"].turn == 0
    assert got[1, "b"].problems == ["missing:q", "type:n", "extra:z"] and got[1, "c"].problems == ["malformed"] and got[1, "d"].problems == ["unknown-tool"] and got[1, "d2"].problems == ["missing:q"]
    assert got[1, "c"].dangling == ["gone"] and got[1, "d"].canonical == '{"arguments":{"a":{"c":[2,1],"d":1},"b":1},"id":"d","name":"other"}'
    assert json.loads(got[None, "a"].canonical) == {"arguments": {"q": "é\n"}, "id": "a", "level": 0, "name": "find"}
    assert tool_calls.link(messages(spark, []), tools).isEmpty()


def test_levels_of_deep_and_wide_graphs(spark):
    rng, rows = random.Random(3), []
    for c in range(4):
        for i in range(40):
            deps = [str(j) for j in range(i) if rng.random() < 0.06] + ([str(i - 1)] if i and c % 2 else [])
            rows.append((c or None, str(i), sorted(set(deps + (["7"] if c == 2 and i == 3 else []) + (["3"] if c == 2 and i == 7 else [])))))
    calls = common.cut(spark.createDataFrame(rows, "conv_id long, id string, depends_on array<string>"), "calls")
    got = {(r.conv_id, r.id): r.level for r in tool_calls.levels(calls).collect()}
    deps, want = {(c, i): d for c, i, d in rows}, {}
    while len(want) < len(deps):
        more = {k: max([want[k[0], d] + 1 for d in v], default=0) for k, v in deps.items() if k not in want and all((k[0], d) in want for d in v)}
        if not more:
            break
        want |= more
    assert got == want and 0 < len(got) < len(rows)


def test_turns_as_calls(spark):
    rows = [(1, 0, "system", "be kind"), (1, 1, "user", None), (1, 2, "assistant", "ok"), (1, 3, "user", "hi there"), (1, None, "user", "x"), (1, 4, "other", "y")]
    got = {r.id: r for r in tool_calls.link(tool_calls.turns_as_calls(messages(spark, rows).withColumn("id", F.lit(1))), tool_calls.TURN_TOOLS).collect()}
    assert {k: (r.level, r.problems, r.n_results) for k, r in got.items()} == {"call-0": (0, [], 0), "call-1": (1, ["missing:prompt"], 1), "call-3": (2, [], 0)}


# ---- line dedup


def plain_lines(rows, least):
    sites, first = defaultdict(set), {}
    for i, text, _, source in rows:
        for line in text.split("\n") if text is not None else ():
            if line.strip(" \t\n\v\f\r"):
                sites[line].add(source)
                if i is not None:
                    first[line] = min(i, first.get(line, i))
    return {(i, text): None if text is None else "\n".join(v for v in text.split("\n") if len(sites[v]) < least or first.get(v) == i) for i, text, _, source in rows}


def test_line_dedup(spark):
    rng = random.Random(1)
    shared = [words(rng, 5) for _ in range(6)]
    rows = [(i, "\n".join([*(s for k, s in enumerate(shared) if rng.random() < 0.3), words(rng, 6), "", rng.choice(shared)]), "en", f"s{rng.randrange(3 if i % 2 else 14)}") for i in range(120)]
    rows += [(500, None, "en", "s1"), (501, "", "en", None), (None, shared[0], "en", "s2"), (502, shared[0] + "\n" + shared[0], None, None), (3, rows[3][1], "en", rows[3][3])]
    docs = table(spark, rows)
    for least in (3, 10):
        got = unclashed(line_dedup.remove_boilerplate(clashing(docs), least), "_lines", "_removed").collect()
        want = plain_lines(rows, least)
        assert sorted((r.doc_id or -1, r.text or "", r.n_chars if r.text is not None else None) for r in got) == sorted((i or -1, want[i, t] or "", len(want[i, t]) if t is not None else None) for i, t, _, _ in rows)
    assert any(r._removed for r in got) and line_dedup.remove_boilerplate(docs.limit(0)).isEmpty()


def test_masks_of_far_apart_lines(spark):
    rng = random.Random(22)
    shared = [f"shared {i}" for i in range(6)]
    rows = [(i, "\n".join(rng.choice(shared) if rng.random() < (0.01 if i % 2 else 0.6) else f"own {i} {k}" for k in range(700)), "en", f"s{i}") for i in range(12)]
    got = {r.doc_id: (r.text, r._lines, r._removed) for r in line_dedup.remove_boilerplate(table(spark, rows), 4).collect()}
    want = plain_lines(rows, 4)
    assert got == {i: (want[i, t], 700, 699 - want[i, t].count("\n")) for i, t, _, _ in rows} and sum(v[2] for v in got.values()) > 1000


def test_near_threshold_lines_are_counted_exactly(spark):
    rows = [(i, f"line {n}", "en", f"s{i}") for n in (299, 300, 301) for i in range(n)]
    got = line_dedup.remove_boilerplate(table(spark, [(k, *r[1:]) for k, r in enumerate(rows)]), min_sites=300, lg_config=8)
    assert {r.text for r in got.where("_removed = 0").groupBy("text").count().where("count > 1").collect()} == {"line 299"}


# ---- personal data


def test_pii_rows(odd, none):
    docs = odd.unionByName(odd.sparkSession.createDataFrame([(9, "at a.b@c.de or 10.0.0.1", "en", "a", 3)], DOCS))
    got = {(r.doc_id, r.text and r.text[:9]): r for r in unclashed(pii.find(clashing(docs)), "base", "spans").collect()}
    assert [(s.kind, s.start, s.end) for s in got[9, "at a.b@c."].base] == [("email", 3, 11), ("ip", 15, 23)] and got[1, None].spans == [] and got[2, ""].spans == []
    assert pii.find(none.select("doc_id", "text")).isEmpty()


# ---- neighbours


def plain_neighbours(x, ids, k):
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    out = {}
    for i in np.flatnonzero(ids % 50 == 0):
        s = (unit @ unit[i]).round(12)
        s[i] = -9
        out[ids[i]] = ids[np.lexsort((ids, -s))][: min(k, len(ids) - 1)].tolist()
    return out


@pytest.mark.parametrize("kind", ["uniform", "clusters", "copies"])
def test_neighbours(spark, kind):
    rng = np.random.default_rng(2)
    x = rng.standard_normal((1500, 16)) + (4 * rng.standard_normal((12, 16)))[np.arange(1500) % 12] * (kind == "clusters")
    if kind == "copies":
        x[:600] = x[0]
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>").repartition(5)
    vectors = ann.valid_vectors(clashing(df), "vec_id", "embedding")
    got = defaultdict(list)
    for r in ann.search(vectors, vectors.where("id % 50 = 0"), chunk=256).orderBy("query_id", "rank").collect():
        got[r.query_id].append(r.vec_id)
    want = plain_neighbours(x, np.arange(1500), 5)
    assert sum(len(set(got[q]) & set(v)) for q, v in want.items()) / (5 * len(want)) >= 0.9
    if kind == "copies":
        assert all(got[q] == v for q, v in want.items() if q < 600)


def test_odd_vectors(spark):
    rows = [(0, [1.0, 0.0]), (1, [2.0, 0.0]), (2, None), (3, [0.0, 0.0]), (4, [float("nan"), 1.0]), (5, [None, 1.0]), (6, [1.0]), (7, [0.0, 3.0]), (1, [2.0, 0.0]), (None, [1.0, 1.0]), (8, [float("inf"), 0.0])]
    vectors = ann.valid_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), "vec_id", "embedding")
    got = ann.search(vectors, vectors.where("id % 50 = 0")).orderBy("rank").collect()
    assert [(r.query_id, r.rank, r.vec_id, r.score) for r in got] == [(0, 1, 1, 1.0), (0, 2, 7, 0.0)]
    empty = vectors.where("id < 0")
    assert ann.search(empty, empty).isEmpty()


# ---- mixing


def test_mixing(spark):
    rng = random.Random(4)
    rows = [(i, words(rng, rng.randint(0, 30)) or None, "en", rng.choice(["a", "a", "a", "b", None, "é"])) for i in range(900)] + [(7, "a b", "en", "b"), (7, "a b", "en", "b"), (None, "a", "en", "a"), (990, "", "en", "zero")]
    docs = clashing(table(spark, rows).drop("n_chars")).repartition(4)
    mixed = unclashed(mixing.mix(docs), "_size", "_draws").cache()
    sizes = defaultdict(int)
    for _, text, _, source in rows:
        sizes[source] += len((text or "").split())
    order = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    want = dict(zip(order, mixing.targets([sizes[s] for s in order], [(5, 2, 1)[i % 3] for i in range(len(order))])))
    taken = defaultdict(int)
    for r in mixed.collect():
        taken[r.source] += r._size * len(r._draws)
        assert len(r._draws) <= 3 and r._source_size == sizes[r.source] and r._target == pytest.approx(want[r.source]) and r._size == len((r.text or "").split())
    assert mixed.count() == len(rows) and all(abs(taken[s] - want[s]) <= 30 for s in order)
    again = mixing.mix(docs.repartition(7))
    key = ["doc_id", "text", "source", "_draws"]
    assert mixed.select(key).exceptAll(again.select(key)).isEmpty()
    shards = mixing.shards_of(mixed, ["doc_id", "shard"]).groupBy("shard").count().collect()
    assert len(shards) == 16 and mixing.mix(docs.limit(0)).isEmpty()
    # the tree deals blocks evenly; a block has some documents here, by a hash
    counts = [r["count"] for r in shards]
    assert max(counts) < 1.6 * min(counts) and sum(counts) == sum(len(r._draws) for r in mixed.collect())
    # few blocks, each of many documents
    coarse = defaultdict(int)
    for r in mixing.mix(docs, blocks=12).collect():
        coarse[r.source] += r._size * len(r._draws)
    assert all(abs(coarse[s] - want[s]) <= 30 for s in order)


def test_rows_without_ids_are_dealt_by_text(spark):
    rng = random.Random(14)
    rows = [(None if i % 3 else i, words(rng, 10), "en", "ab"[i % 2]) for i in range(600)]
    got = mixing.mix(table(spark, rows)).collect()
    assert len({d.shard for r in got if r.doc_id is None for d in r._draws}) == 16 
    taken, wanted = defaultdict(int), {}
    for r in got:
        taken[r.source] += r._size * len(r._draws)
        wanted[r.source] = r._target
    assert all(abs(taken[s] - wanted[s]) <= 20 for s in wanted)


# ---- near duplicates


def plain_components(rows):
    prints = [plain_fingerprint(t) for _, t in rows]
    parent = list(range(len(rows)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if bin(prints[i] ^ prints[j]).count("1") <= 2 or (rows[i][0] is not None and rows[i][0] == rows[j][0]):
                parent[root(i)] = root(j)
    groups = defaultdict(list)
    for i, (d, _) in enumerate(rows):
        groups[root(i)].append(d)
    low = {g: min([d for d in v if d is not None], default=None) for g, v in groups.items()}
    return sorted((d if d is not None else -1, p, low[root(i)] if low[root(i)] is not None else -1) for i, ((d, _), p) in enumerate(zip(rows, prints)))


@pytest.mark.parametrize("limit", [2, 8, 1000])
def test_simhash_components(spark, limit):
    rng = random.Random(5)
    seeds = [words(rng, 60) for _ in range(8)]
    rows = []
    for i in range(160):
        w = rng.choice(seeds).split()
        for _ in range(rng.choice((0, 0, 1, 1, 2))):
            w[rng.randrange(len(w))] = rng.choice(("new", "old", "red"))
        rows.append((i, " ".join(w)))
    rows += [(300, None), (301, ""), (302, "one"), (303, "ONE"), (304, "two words"), (None, rows[0][1]), (5, rows[5][1]), (305, " ".join(["same"] * 5000))]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = sorted((r.doc_id if r.doc_id is not None else -1, r.fp & (1 << 64) - 1, r.component_id if r.component_id is not None else -1) for r in simhash.near_duplicates(clashing(docs), limit).collect())
    assert got == plain_components(rows)


def test_links_of_a_dense_cluster(spark):
    """All fingerprints within two bits of each other and chains of them, through every way of a posting list."""
    rng = random.Random(6)
    centre = rng.getrandbits(64)
    prints = {centre} | {centre ^ (1 << i) ^ (1 << j) for i in range(0, 64, 3) for j in range(i)} | {centre ^ 0b1111, centre ^ 0b111111}
    signed = [p - (1 << 64) if p >> 63 else p for p in prints]
    nodes = spark.createDataFrame([(p, i) for i, p in enumerate(sorted(signed))], "node long, own long")
    for limit in (1, 8):
        links = simhash.links(nodes.select(F.col("node").alias("fp")), limit)
        assert links.where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) > 2).isEmpty()
        assert {r.label for r in simhash.components(links, nodes).collect()} == {0}


def test_keep_one(odd, none):
    kept = simhash.keep_one(odd)
    assert unclashed(simhash.keep_one(clashing(odd))).count() == 4
    assert sorted(r.doc_id or -1 for r in kept.collect()) == [-1, 1, 4, 5] and kept.columns == odd.columns and simhash.keep_one(none).isEmpty()


def test_keep_one_of_irregular_ids(spark):
    rng = random.Random(13)
    a, b, c, d = ([f"{k}{rng.randrange(500)}" for _ in range(60)] for k in "abcd")
    prints = lambda w: plain_fingerprint(" ".join(w))
    apart = lambda x, y: bin(prints(x) ^ prints(y)).count("1")
    # a chain whose ends are too far apart to link without the middle, which has no id
    while True:
        ends = [d[:i] + [f"e{rng.randrange(9**6)}"] + d[i + 1 :] for i in (rng.randrange(60), rng.randrange(60))]
        if all(1 <= apart(d, e) <= 2 for e in ends) and apart(*ends) > 2:
            break
    rows = [(1, a), (2, a), (2, b), (None, c), (None, c), (None, a), (7, ends[0]), (None, d), (8, ends[1])]
    got = simhash.keep_one(table(spark, [(i, " ".join(w), "en", "s") for i, w in rows])).collect()
    assert sorted((r.doc_id or -1, r.text[0]) for r in got) == [(-1, "c"), (1, "a"), (2, "b"), (7, ends[0][0][0])]


# ---- quality and language


def test_quality(spark, odd, none):
    rng = random.Random(7)
    rows = [(i, words(rng, 20) if i % 2 else "###".join(words(rng, 12).split()), "en", "a") for i in range(200)]
    docs = table(spark, rows)
    labels = docs.select("doc_id", (F.col("doc_id") % 2).cast("int").alias("quality")).unionByName(spark.createDataFrame([(None, 1), (900, 1), (3, None), (5, 1), (5, 1)], "doc_id long, quality int"))
    model = quality.train(docs.where("doc_id < 100"), labels.where("doc_id < 100"))
    got = unclashed(quality.score(clashing(docs.unionByName(odd)), model), "quality_score").collect()
    assert sum((r.quality_score > 0.5) == r.doc_id % 2 for r in got if r.doc_id is not None and 100 <= r.doc_id < 200) >= 98 and all(0 <= r.quality_score <= 1 for r in got)
    assert len({r.quality_score for r in got if r.doc_id in (1, 2, 3) and not (r.text or "").strip()}) == 1
    assert quality.train(none, labels.limit(0)) is None and {r.quality_score for r in quality.score(odd, None).collect()} == {0.5} and quality.score(none, model).isEmpty()


def test_language(spark, odd, none):
    stock = {"en": "the of and with from this that", "de": "der die und nicht mit von eine", "fr": "le la les des est une avec", "es": "el los que una por con del"}
    rng = random.Random(8)
    rows = [(i, words(rng, 15, v.split()), k, "a") for i, (k, v) in enumerate(list(stock.items()) * 30)]
    docs = table(spark, rows)
    model = language_id.train(docs.where("doc_id < 80"))
    got = unclashed(language_id.predict(clashing(docs.unionByName(odd)), model), "lang_pred", "lang_score").collect()
    assert sum(r.lang_pred == r.lang for r in got if r.doc_id is not None and 80 <= r.doc_id) >= 39 and all(0 <= r.lang_score <= 1 for r in got)
    assert all(r.lang_pred == "und" and r.lang_score == 0 for r in got if not (r.text or "").strip()) and model.families == ["germanic", "romance"]
    assert language_id.train(none) is None and {r.lang_pred for r in language_id.predict(odd, None).collect()} == {"und"} and language_id.predict(none, model).isEmpty()
    one = language_id.train(docs.where("lang = 'fr'"))
    assert {r.lang_pred for r in language_id.predict(docs, one).collect()} == {"fr"}


def test_learners_are_bounded_in_rows_and_bytes(spark):
    rows = [(i % 7, f"text {i} " + "x" * (i % 5) * 10, "en", "a") for i in range(500)] + [(8, "y" * 500, "en", "a"), (9, None, "en", "a")]
    ids = spark.createDataFrame([(i, i % 2) for i in range(12)], "doc_id long, quality int")
    got = learning.bounded_texts(table(spark, rows), ids, "quality", longest=100).collect()
    assert len(got) == 7 and all(len(r.text) <= 100 for r in got)


def test_bounded_samples(spark):
    rows = spark.range(5000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 100 == 0, "rare").otherwise("common").alias("k"))
    got = {r[0]: r[1] for r in learning.bounded_ids(rows, "doc_id", "k", 200).groupBy("k").count().collect()}
    assert got["rare"] == 50 and 120 < got["common"] < 280


# ---- decontamination


def test_decontamination(spark, odd, none):
    rng = random.Random(9)
    stock = [f"w{i}" for i in range(400)] + ["the", "of"] * 60
    items = [(i, words(rng, 25, stock)) for i in range(30)] + [(77, None), (99, None), (98, " .")]
    items[5] = (5, items[4][1])
    bench = spark.createDataFrame([*items, (None, "x y z a b c d e")], "item_id long, text string")
    held, rows = {}, []
    for i in range(300):
        text = words(rng, 80, stock)
        if i % 3 == 0:
            k = 0 if i % 2 else rng.randrange(30)  # item 0 stands in a sixth of all documents
            w = items[k][1].split()
            for _ in range(i % 4):
                w[rng.randrange(len(w))] = "edited"
            text = text[:200] + " " + " ".join(w).upper() + ", " + text[200:]
            held[i] = min(j for j, t in items if t == items[k][1])
        rows.append((i, text, "en", "a"))
    docs = table(spark, rows)
    for n in (1000, 7):
        got = defaultdict(dict)
        for r in decontaminate.matches(clashing(docs.unionByName(odd)), bench, block_items=n).collect():
            got[r.doc_id][r.item_id] = r.score
        assert set(got) == set(held) and all(max(v, key=v.get) in (held[i], 5) for i, v in got.items())
    assert all(max(got[i].values()) == 1 for i in held if i % 4 == 0)
    kept = unclashed(decontaminate.clean(clashing(docs.unionByName(odd)), bench))
    assert kept.count() == 200 + odd.count() and set(kept.columns) == {*docs.columns, *CLASH, *ADDED}
    assert decontaminate.matches(none, bench).isEmpty() and decontaminate.matches(docs, bench.limit(0)).isEmpty() and decontaminate.clean(docs, bench.limit(0)).count() == 300


def test_short_items_match_verbatim_only(spark):
    bench = spark.createDataFrame([(1, "Too short, this"), (2, "zebra"), (3, "a b c d e"), (4, "TOO short THIS"), (5, "?")], "item_id long, text string")
    texts = ["it is too SHORT. this one", "too short of this", "a zebra a b c d", "x a b c d e y zebra", "", None, "too short this too short this"]
    docs = table(spark, [(i, t, "en", "a") for i, t in enumerate(texts)])
    longer = bench.unionByName(spark.createDataFrame([(9, "some other item of many different words altogether")], bench.schema))
    for items in (bench, longer):
        assert sorted((r.doc_id, r.item_id, r.score, r.end_word) for r in decontaminate.matches(docs, items).collect()) == [(0, 1, 1.0, 5), (2, 2, 1.0, 2), (3, 2, 1.0, 8), (3, 3, 1.0, 6), (6, 1, 1.0, 3)]
        assert sorted(r.doc_id for r in decontaminate.clean(docs, items).collect()) == [1, 4, 5]


def test_item_blocks_are_bounded_in_characters(spark, monkeypatch):
    rng = random.Random(15)
    bench = spark.createDataFrame([(i, words(rng, 20)) for i in range(20)], "item_id long, text string")
    whole = sorted(decontaminate.matches(table(spark, [(i, words(rng, 9) + " " + r.text, "en", "a") for i, r in enumerate(bench.collect())]), bench).collect())
    rng = random.Random(15)
    monkeypatch.setattr(decontaminate, "BLOCK_CHARS", 400)
    again = spark.createDataFrame([(i, words(rng, 20)) for i in range(20)], "item_id long, text string")
    assert len(list(decontaminate._blocks(again, 3, 6, 5000))) > 3
    assert sorted(decontaminate.matches(table(spark, [(i, words(rng, 9) + " " + r.text, "en", "a") for i, r in enumerate(again.collect())]), again).collect()) == whole


def test_decontamination_finds_edited_copies_however_many(spark):
    rng = random.Random(12)
    item = [f"q{i}" for i in range(40)]
    edited = " ".join("other" if i % 5 == 4 else w for i, w in enumerate(item))
    common = " ".join(item[:3])  # a hot n-gram alone is no copy
    bench = spark.createDataFrame([(7, " ".join(item)), (8, " ".join(item[:3] + [f"z{i}" for i in range(30)]))], "item_id long, text string")
    stock = [f"w{i}" for i in range(300)]
    for n, copies in ((200, 1), (900, 1), (1500, 40)):
        rows = [(i, words(rng, 30, stock) + " " + (edited if i < copies else common if i % 3 == 0 else "") + " " + words(rng, 30, stock), "en", "a") for i in range(n)]
        docs = table(spark, rows)
        got = decontaminate.matches(docs, bench).collect()
        assert {(r.doc_id, r.item_id) for r in got} == {(i, 7) for i in range(copies)} and all(0.68 < r.score < 0.72 for r in got)
        assert decontaminate.clean(docs, bench).count() == n - copies
        # how rare is rare changes what is aligned at once, not what is found
        for rare in (0.0, 1.0):
            assert sorted(decontaminate.matches(docs, bench, rare=rare, min_score=0.05).collect()) == sorted(decontaminate.matches(docs, bench, min_score=0.05).collect())


# ---- urls


def test_url_rules(spark):
    urls = ["http://A.example.NET/en/1", "http://example.net/fr/", "http://b.org/fr/x?y", "http://b.org/de/", "http://example.com/de/1#t", "http://notexample.com/de/", "http://x.net", "net/", None, "", "HTTPS://u@h:80/p?q", "a://b://c/d", "http://net/"]
    pages = spark.createDataFrame([(i, u, "h") for i, u in enumerate(urls)] + [(0, urls[0], "h")], "page_id long, url string, html string")
    got = {r.page_id: r for r in unclashed(url_filter.judge(clashing(pages)), "host", "path", "rule", "ruled", "score", "threshold").collect()}
    assert [(got[i].host, got[i].path) for i in range(13)] == [("a.example.net", "/en/1"), ("example.net", "/fr/"), ("b.org", "/fr/x"), ("b.org", "/de/"), ("example.com", "/de/1"), ("notexample.com", "/de/"), ("x.net", ""), ("", ""), ("", ""), ("", ""), ("u@h:80", "/p"), ("b:", "//c/d"), ("net", "/")]
    assert [got[i].rule for i in range(13)] == ["example.net/en/", "net/", "org/fr/", None, "example.com/de/", None, None, None, None, None, None, None, "net/"]
    assert url_filter.judge(pages).count() == 14 and url_filter.judge(pages.limit(0)).isEmpty()


def test_url_rules_are_taken_literally(spark):
    pages = spark.createDataFrame([(1, "http://axb.com/p_q/"), (2, "http://a_b.com/p_q/x"), (3, "http://o'x.com/p%/"), (4, "http://o'x.com/pp/")], "page_id long, url string")
    got = {r.page_id: r.ruled for r in url_filter.split(pages, (("a_b.com", "/p_q/", "block"), ("o'x.com", "/p%/", "allow"))).collect()}
    assert got == {1: None, 2: "block", 3: "allow", 4: None}


def plain_url_scores(urls, verdicts):
    """Mean log ratio of each url, by counts of every context length and the smoothing written out."""
    def text(u):
        rest = u.split("://", 1)[1]
        host = re.split(r"[/?#]", rest)[0]
        path = re.split(r"[?#]", rest[len(host) :])[0]
        return "///" + re.sub("[^a-z0.-]", "/", re.sub("[0-9]", "0", (host + path).lower()))

    counts = defaultdict(lambda: [0, 0])
    for u in urls:
        if verdicts[u] is not None and int(hashlib.md5(u.encode()).hexdigest()[:7], 16) % url_filter.FOLDS:
            t = text(u)
            for i in range(3, len(t)):
                for k in range(4):
                    counts["=" + t[i - k : i + 1]][verdicts[u] == "block"] += 1
                    counts["<" + t[i - k : i]][verdicts[u] == "block"] += 1
    out = {}
    for u in urls:
        t, total = text(u), 0.0
        for i in range(3, len(t)):
            p = [1 / 30, 1 / 30]
            for k in range(4):
                p = [(counts["=" + t[i - k : i + 1]][c] + 4 * p[c]) / (counts["<" + t[i - k : i]][c] + 4) for c in (0, 1)]
            total += math.log(p[1] / p[0])
        out[u] = total / (len(t) - 3)
    return out


def test_url_models(spark):
    rng = random.Random(10)
    rules = (("good.org", "/", "allow"), ("casino.com", "/", "block"))
    good = [f"http://{words(rng, 1)}{rng.randrange(9)}.good.org/read/{words(rng, 1)}/{rng.randrange(99)}" for _ in range(120)]
    bad = [f"http://www.{words(rng, 1)}.casino.com/slots/{words(rng, 1)}?{rng.randrange(99)}" for _ in range(80)]
    new_good, new_bad = [f"http://goodread.net/read/{words(rng, 1)}/{i}" for i in range(20)], [f"http://casinoslots.net/slots/{words(rng, 1)}/{i}" for i in range(20)]
    urls = sorted(set(good + bad + new_good + new_bad))
    pages = spark.createDataFrame([(i, u) for i, u in enumerate(urls)] + [(0, urls[0])], "page_id long, url string").repartition(3)
    judged = url_filter.judge(pages, rules).cache()
    got = {r.url: r for r in judged.collect()}
    want = plain_url_scores(urls, {u: got[u].ruled for u in urls})
    assert all(got[u].score == pytest.approx(want[u], abs=1e-9) for u in urls)
    # what the rules say of some hosts is carried over to hosts that no rule knows
    assert sum(got[u].score > got[u].threshold for u in new_good) <= 2 and sum(got[u].score > got[u].threshold for u in new_bad) >= 18
    told = {r.ruled: (r.n, r.blocked) for r in url_filter.agreement(judged).collect()}
    assert told["allow"][0] > 5 and told["allow"][1] <= 1 and told["block"][1] >= told["block"][0] - 1
    assert {r.threshold for r in url_filter.judge(pages, ()).collect()} == {None}


# ---- pipeline


def test_pipeline_stages(spark, tmp_path):
    rng = random.Random(11)
    stock = {"en": "the of and with from this that tower river stone".split(), "de": "der die und nicht mit von eine turm fluss stein".split()}
    item = words(rng, 30, [f"q{i}" for i in range(200)])
    licence = "this line stands on every site"
    rows = []
    for i in range(240):
        lang = "en" if i % 2 else "de"
        text = words(rng, 60, stock[lang]) + "\n" + licence
        rows.append((i, text + ("\n" + item if i % 20 == 0 else ""), lang, f"s{i % 12}"))
    rows += [(1000 + i, rows[7][1], "en", f"s{i % 3}") for i in range(9)] + [(2000, None, "en", "s1"), (2001, "12345 !!", "de", "s2")]
    table(spark, rows).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    docs, kept = spark.read.parquet(str(tmp_path / "documents.parquet")), []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = common.cut(stage(spark, docs, str(tmp_path)), name)
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
        kept.append({r.doc_id: r.text for r in docs.collect()})
    every = {r[0] for r in rows}
    assert set(kept[0]) == every - {2000, 2001} and set(kept[1]) == set(kept[0])
    assert [i for i, t in kept[1].items() if licence in t] == [0]
    assert set(kept[2]) == set(kept[1]) - {1000 + i for i in range(9)}
    assert set(kept[3]) == set(kept[2]) - set(range(0, 240, 20))
    mixed = corpus_pipeline.run(spark, str(tmp_path)).cache()
    assert set(mixed.columns) == {"doc_id", "text", "lang", "source", "n_chars", "shard", "turn", "place"} and {r.doc_id for r in mixed.collect()} <= set(kept[3])
    empty = docs.limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, str(tmp_path)).isEmpty()
