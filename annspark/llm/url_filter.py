"""URL filter: longest matching rule, else a character language-model ratio. SQL only.

Host and path are cut out of the url; the longest rule whose host is the url's host or a parent domain
of it, and whose path begins the url's path, gives the verdict. Urls without a rule are judged by two
smoothed variable-order Markov models of characters, one of rejected and one of accepted urls: the sum of the log ratios over the
characters of host and path, divided by their number, against a threshold.

Classes. The accepted and the rejected urls are those that the rules allow and block: what the owner of the rules settled by hand is carried over to the urls that
no rule fits. No word list is involved. Distinct urls of either class are dealt by a hash: three parts of four fit the models, the fourth calibrates.

Models. Text is folded to 30 symbols (a-z, one digit, dot, hyphen, slash for all else) and padded in front. Every n-gram
up to ``ORDER`` + 1 symbols is counted in both classes over the whole table. The probability after a context is Dirichlet-smoothed
towards that after the context without its first symbol, down to one symbol and the uniform one; contexts that a
class has not seen fall back to shorter ones. An n-gram table has at most 30 ** 4 rows (about 30 MB), whatever the input, so it is broadcast.

Calibration: the threshold is the point between the mean scores of accepted and rejected urls of the calibrating part that is as
many standard deviations of either from its mean. ``agreement`` tells how often the models alone say what the rules say on that part.

Edge cases: a null url, or one without ``://``, has an empty host and path, no rule, score 0 and is allowed; if
either class is empty in either part, all urls without a rule are allowed; a score equal to the threshold is allowed; repeated urls get the same verdict; a very long url
costs time in proportion to its length; an empty table gives no rows; further columns pass through ``judge``, and columns named like those that it adds
(host, path, rule, ruled, score, threshold) are replaced by them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, table, without

#: The contract's rules, (host, path, verdict).
RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))
ORDER = 3
#: Weight of the shorter context in the probability after a longer one.
PRIOR = "4e0"
#: One url of so many calibrates.
FOLDS = 4
PAD = "/" * ORDER
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _quoted(text: str) -> str:
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"


def split(pages: DataFrame, rules=RULES) -> DataFrame:
    """``pages`` with host, path, rule and ruled (the rule's verdict)."""
    pages = without(pages, "host", "path", "rule", "ruled", "score", "threshold")
    host = F.coalesce(F.translate(F.regexp_extract("url", "://([^/?#]*)", 1), _UPPER, _LOWER), F.lit(""))
    path = F.coalesce(F.regexp_extract("url", "://[^/?#]*([^?#]*)", 1), F.lit(""))
    found = pages.withColumns({"host": host, "path": path})
    rule = ruled = F.lit(None).cast("string")
    for h, p, verdict in sorted(rules, key=lambda r: len(r[0] + r[1])):
        fits = f"(host = {_quoted(h)} OR endswith(host, {_quoted('.' + h)})) AND startswith(path, {_quoted(p)})"
        # longer rules are asked first
        rule, ruled = (F.when(F.expr(fits), F.lit(v)).otherwise(old) for v, old in ((h + p, rule), (verdict, ruled)))
    return found.withColumns({"rule": rule, "ruled": ruled})


def _texts() -> str:
    """url, its folded and padded text, its class (null without a rule) and whether it calibrates, for each distinct url."""
    folded = f"regexp_replace(regexp_replace(translate(concat(host, path), '{_UPPER}', '{_LOWER}'), '[0-9]', '0'), '[^a-z0.-]', '/')"
    return f"""SELECT url, concat('{PAD}', {folded}) AS u, ruled = 'block' AS bad, conv(substring(md5(url), 1, 7), 16, 10) % {FOLDS} = 0 AS apart
      FROM (SELECT DISTINCT url, host, path, ruled FROM split WHERE host <> '' OR path <> '') AS distinct_urls"""


def _places(low: int) -> str:
    return f" LATERAL VIEW explode(sequence({low}, length(u))) t AS i"


def _model() -> str:
    """g, lr (log ratio of its last symbol after the others) and back (what an unseen symbol after g costs the ratio)."""
    each = f"""SELECT substring(u, i - k, k + 1) AS g, count_if(bad) AS r, count_if(NOT bad) AS a
      FROM urls{_places(ORDER + 1)} LATERAL VIEW explode(sequence(0, {ORDER})) o AS k WHERE bad IS NOT NULL AND NOT apart GROUP BY substring(u, i - k, k + 1)"""
    steps = [f"grams AS ({each})", "contexts AS (SELECT substring(g, 1, length(g) - 1) AS g, sum(r) AS nr, sum(a) AS na FROM grams GROUP BY substring(g, 1, length(g) - 1))"]
    steps.append(
        f"p1 AS (SELECT grams.g, (r + {PRIOR} / 30) / (nr + {PRIOR}) AS pr, (a + {PRIOR} / 30) / (na + {PRIOR}) AS pa FROM grams JOIN contexts ON contexts.g = '' WHERE length(grams.g) = 1)"
    )
    for k in range(2, ORDER + 2):
        steps.append(
            f"p{k} AS (SELECT grams.g, (r + {PRIOR} * s.pr) / (nr + {PRIOR}) AS pr, (a + {PRIOR} * s.pa) / (na + {PRIOR}) AS pa"
            f" FROM grams JOIN contexts ON contexts.g = substring(grams.g, 1, {k - 1}) JOIN p{k - 1} s ON s.g = substring(grams.g, 2, {k - 1}) WHERE length(grams.g) = {k})"
        )
    every = " UNION ALL ".join(f"SELECT g, pr, pa FROM p{k}" for k in range(1, ORDER + 2))
    return f"WITH {', '.join(steps)} SELECT e.g, ln(pr / pa) AS lr, coalesce(ln((na + {PRIOR}) / (nr + {PRIOR})), 0e0) AS back FROM ({every}) e LEFT JOIN contexts ON contexts.g = e.g"


def _scores() -> str:
    """url, bad, apart, score for each distinct url."""
    value = "coalesce(g1.lr, 0e0)"
    for k in range(2, ORDER + 2):
        value = f"coalesce(g{k}.lr, {value} + coalesce(c{k - 1}.back, 0e0))"
    grams = " ".join(f"LEFT JOIN model g{k} ON g{k}.g = substring(u, i - {k - 1}, {k})" for k in range(ORDER + 1, 0, -1))
    contexts = " ".join(f"LEFT JOIN model c{k} ON c{k}.g = substring(u, i - {k}, {k})" for k in range(ORDER, 0, -1))
    hint = ", ".join([f"g{k}" for k in range(1, ORDER + 2)] + [f"c{k}" for k in range(1, ORDER + 1)])
    return f"SELECT /*+ BROADCAST({hint}) */ url, bad, apart, avg({value}) AS score FROM (SELECT url, bad, apart, u, i FROM urls{_places(ORDER + 1)}) AS place {grams} {contexts} GROUP BY url, bad, apart"


def _threshold(scores: DataFrame) -> float | None:
    """Between the means of both classes of the calibrating part, in proportion to their deviations; None without both."""
    got = {r.bad: r for r in scores.where("apart AND bad IS NOT NULL").groupBy("bad").agg(F.avg("score").alias("mean"), F.stddev_pop("score").alias("off")).collect()}
    if len(got) < 2:
        return None
    bad, good = got[True], got[False]
    return (good.mean * (bad.off + 1e-9) + bad.mean * (good.off + 1e-9)) / (good.off + bad.off + 2e-9)


def judge(pages: DataFrame, rules=RULES) -> DataFrame:
    """``pages`` (with a url) with host, path, rule, ruled, score (null where there is no text) and threshold."""
    spark, parted = pages.sparkSession, split(pages, rules)
    urls = _sql(spark, _texts(), split=parted.select("url", "host", "path", "ruled"))
    model = cut(_sql(spark, _model(), urls=urls), "url-model")
    scores = cut(_sql(spark, _scores(), urls=urls, model=model), "url-scores")
    threshold = _threshold(scores)
    scored = parted.join(scores.select("url", "score"), "url", "left").select(*parted.columns, "score")
    return scored.withColumn("threshold", F.lit(threshold).cast("double"))


def agreement(judged: DataFrame) -> DataFrame:
    """(ruled, n, blocked): how many distinct urls of the calibrating part have either rule verdict, and how many of them the models alone block."""
    apart = judged.where(F.col("ruled").isNotNull() & (F.conv(F.substring(F.md5("url"), 1, 7), 16, 10) % FOLDS == 0)).select("url", "ruled", "score", "threshold").distinct()
    return apart.groupBy("ruled").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("score") > F.col("threshold")).alias("blocked"))


def _sql(spark, text: str, **frames: DataFrame) -> DataFrame:
    """Spark SQL over named frames, as views of these names for the length of the call."""
    for name, frame in frames.items():
        frame.createOrReplaceTempView(f"_url_{name}")
    views = ", ".join(f"{name} AS (SELECT * FROM _url_{name})" for name in frames)
    text = text.strip()
    joined = f"WITH {views}, {text[5:]}" if text.startswith("WITH ") else f"WITH {views} {text}"
    try:
        return spark.sql(joined)
    finally:
        for name in frames:
            spark.catalog.dropTempView(f"_url_{name}")


def query(spark, sf_dir):
    judged = judge(table(spark, sf_dir, "pages"))
    verdict = F.coalesce("ruled", F.when(F.col("score") > F.col("threshold"), "block").otherwise("allow"))
    return judged.select("page_id", "host", "path", "rule", verdict.alias("verdict"))


#: Written apart from the engine: rules as a table, and each place's probability by the plain recursion over four orders.
SQL = r"""
WITH cut1 AS (SELECT page_id, url, row_number() OVER () AS rid, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
cut2 AS (SELECT *, regexp_extract(rest, '^[^/?#]*') AS raw FROM cut1),
parted AS (SELECT page_id, url, rid, translate(raw, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(substr(rest, length(raw) + 1), '^[^?#]*') AS path FROM cut2),
rules(h, p, v) AS (VALUES ('net', '/', 'block'), ('example.net', '/en/', 'allow'), ('example.com', '/de/', 'block'), ('org', '/fr/', 'allow')),
fit AS (SELECT rid, h || p AS rule, v FROM parted, rules WHERE (host = h OR suffix(host, '.' || h)) AND prefix(path, p) QUALIFY row_number() OVER (PARTITION BY rid ORDER BY length(h || p) DESC) = 1),
whole AS (SELECT parted.*, rule, v FROM parted LEFT JOIN fit USING (rid)),
texts AS (SELECT url, v, ('0x' || substr(md5(url), 1, 7))::INT % 4 = 0 AS apart,
    '///' || regexp_replace(regexp_replace(translate(host || path, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[0-9]', '0', 'g'), '[^a-z0.-]', '/', 'g') AS u
  FROM whole WHERE host <> '' OR path <> '' GROUP BY url, host, path, v),
spots AS (SELECT url, v, apart, substr(u, i, 1) AS s, substr(u, i - 1, 1) AS b, substr(u, i - 2, 1) AS c, substr(u, i - 3, 1) AS d FROM texts, unnest(range(4, length(u) + 1)) t(i)),
learned AS (SELECT s, b, c, d, count(*) FILTER (v = 'block') AS r, count(*) FILTER (v = 'allow') AS a FROM spots WHERE v IS NOT NULL AND NOT apart GROUP BY ALL),
n0 AS (SELECT sum(r) AS r, sum(a) AS a FROM learned),
f1 AS (SELECT s, sum(r) AS r, sum(a) AS a FROM learned GROUP BY ALL), n1 AS (SELECT b, sum(r) AS r, sum(a) AS a FROM learned GROUP BY ALL),
f2 AS (SELECT s, b, sum(r) AS r, sum(a) AS a FROM learned GROUP BY ALL), n2 AS (SELECT b, c, sum(r) AS r, sum(a) AS a FROM learned GROUP BY ALL),
f3 AS (SELECT s, b, c, sum(r) AS r, sum(a) AS a FROM learned GROUP BY ALL), n3 AS (SELECT b, c, d, sum(r) AS r, sum(a) AS a FROM learned GROUP BY ALL),
o1 AS (SELECT spots.*, (coalesce(f1.r, 0) + 4e0 / 30) / (n0.r + 4e0) AS pr, (coalesce(f1.a, 0) + 4e0 / 30) / (n0.a + 4e0) AS pa FROM spots CROSS JOIN n0 LEFT JOIN f1 USING (s)),
o2 AS (SELECT o1.* EXCLUDE (pr, pa), (coalesce(f2.r, 0) + 4e0 * pr) / (coalesce(n1.r, 0) + 4e0) AS pr, (coalesce(f2.a, 0) + 4e0 * pa) / (coalesce(n1.a, 0) + 4e0) AS pa FROM o1 LEFT JOIN f2 USING (s, b) LEFT JOIN n1 USING (b)),
o3 AS (SELECT o2.* EXCLUDE (pr, pa), (coalesce(f3.r, 0) + 4e0 * pr) / (coalesce(n2.r, 0) + 4e0) AS pr, (coalesce(f3.a, 0) + 4e0 * pa) / (coalesce(n2.a, 0) + 4e0) AS pa FROM o2 LEFT JOIN f3 USING (s, b, c) LEFT JOIN n2 USING (b, c)),
o4 AS (SELECT o3.* EXCLUDE (pr, pa), (coalesce(l.r, 0) + 4e0 * pr) / (coalesce(n3.r, 0) + 4e0) AS pr, (coalesce(l.a, 0) + 4e0 * pa) / (coalesce(n3.a, 0) + 4e0) AS pa FROM o3 LEFT JOIN learned l USING (s, b, c, d) LEFT JOIN n3 USING (b, c, d)),
scored AS (SELECT url, v, apart, avg(ln(pr / pa)) AS score FROM o4 GROUP BY ALL),
sides AS (SELECT avg(score) FILTER (v = 'allow') AS ma, avg(score) FILTER (v = 'block') AS mr, stddev_pop(score) FILTER (v = 'allow') AS sa, stddev_pop(score) FILTER (v = 'block') AS sr FROM scored WHERE apart)
SELECT page_id, host, path, rule, coalesce(v, CASE WHEN score > (ma * (sr + 1e-9) + mr * (sa + 1e-9)) / (sa + sr + 2e-9) THEN 'block' ELSE 'allow' END) AS verdict
FROM whole LEFT JOIN (SELECT url, score FROM scored) USING (url) CROSS JOIN sides
"""
