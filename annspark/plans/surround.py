"""Queries around the index: attributes of neighbours, reports over sweeps, results compared, events and their index versions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.tables import load
from ..sources.vectors import doc_vectors, event_vectors, order_vectors
from ..streaming.streams import windowed_counts


def micros(df: DataFrame, column: str):
    """Microseconds of a time as written, whatever the session's time zone: the given tables have times without zone."""
    if dict(df.dtypes).get(column) == "timestamp":
        return F.unix_micros(column)
    return F.unix_micros(F.to_timestamp(F.concat(F.col(column).cast("string"), F.lit("Z"))))


def star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Revenue and orders by region and nation: attributes that are attached to order vectors."""
    l, o, c, n, r = (load(spark, sf_dir, t) for t in ("lineitem", "orders", "customer", "nation", "region"))
    priced = l.groupBy("l_orderkey").agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("paid"))
    joined = priced.join(o, priced.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    return joined.groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("orders"), F.round(F.sum("paid"), 2).alias("revenue"))


def rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order counts and mean totals over status and priority, with subtotals."""
    o = load(spark, sf_dir, "orders")
    return o.rollup("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("o_totalprice"), 2).alias("mean_total"), F.grouping_id().cast("long").alias("level"))


def cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = load(spark, sf_dir, "documents")
    return d.cube("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"), F.grouping_id().cast("long").alias("level")).where("n >= 5")


def event_windows(kind: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        found = windowed_counts(load(spark, sf_dir, "events"), kind)
        return found.select(micros(found, "start").alias("start_us"), micros(found, "end").alias("end_us"), "event_type", "n", F.round("total", 2).alias("total"))

    return run


def event_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How often each key stands in the events' JSON."""
    e = load(spark, sf_dir, "events")
    return e.select("event_type", F.explode(F.json_object_keys("props")).alias("key")).groupBy("event_type", "key").agg(F.count(F.lit(1)).alias("n"))


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of each user: events at most 30 minutes apart, by lag and a running sum."""
    e = load(spark, sf_dir, "events")
    e = e.select("user_id", "event_id", micros(e, "ts").alias("us"))
    w = Window.partitionBy("user_id").orderBy("us", "event_id")
    new = F.when(F.col("us") - F.lag("us").over(w) <= 1_800_000_000, 0).otherwise(1)
    numbered = e.withColumn("new", new).withColumn("session", F.sum("new").over(w.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return numbered.groupBy("user_id", "session").agg(F.count(F.lit(1)).alias("n"), (F.max("us") - F.min("us")).alias("length_us"))


def index_versions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each event with the index version in force: the last ``purchase`` up to it (-1: none yet), as an as-of join by union and a running last value."""
    e = load(spark, sf_dir, "events")
    e = e.select("event_id", "event_type", micros(e, "ts").alias("us")).withColumn("day", F.floor(F.col("us") / 86_400_000_000))
    versions = e.where("event_type = 'purchase'").select("day", "us", F.col("event_id").alias("version"))
    both = e.select("day", "us", "event_id", F.lit(None).cast("long").alias("version")).unionByName(versions.select("day", "us", F.lit(None).cast("long").alias("event_id"), "version"))
    # days bound the sort; a day without a version so far takes the last of the days before
    w = Window.partitionBy("day").orderBy("us", F.col("version").isNull(), "version", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    within = both.withColumn("in_day", F.last("version", True).over(w))
    ends = versions.groupBy("day").agg(F.max_by("version", F.struct("us", "version")).alias("last"))
    days = e.select("day").distinct().join(ends, "day", "left").withColumn("carried", F.last("last", True).over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)))
    return within.where("event_id IS NOT NULL").join(F.broadcast(days.select("day", "carried")), "day").select("event_id", F.coalesce("in_day", "carried", F.lit(-1)).alias("version"))


def rounded(column: str, places: int):
    """A double to so many decimals as the oracles do it, halves of the scaled binary number away from 0; Spark's own rounding takes the printed decimals, so 57 / 800 would become .0713."""
    scale = float(10**places)
    x = F.col(column)
    return F.signum(x) * F.floor(F.abs(x) * scale + 0.5) / scale


def vector_table(name: str):
    """(vec_id, slot, value) of a vector table, so that it can be compared."""
    make = {"doc": doc_vectors, "order": order_vectors, "event": event_vectors}[name]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return make(spark, sf_dir).select("vec_id", F.posexplode("embedding").alias("slot", "value")).select("vec_id", F.col("slot").cast("long").alias("slot"), rounded("value", 4).alias("value")).where("value <> 0")

    return run


def label_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors of each label by four ranges of the first component, pivoted."""
    x = F.element_at("embedding", 1).cast("double")
    e = load(spark, sf_dir, "embeddings").select("label", F.greatest(F.lit(1), F.least(F.lit(4), F.floor((x + 0.2) / 0.1).cast("int") + 1)).alias("q"))
    return e.groupBy(F.col("label").cast("long").alias("label")).pivot("q", [1, 2, 3, 4]).agg(F.count(F.lit(1))).select("label", *[F.coalesce(F.col(str(i)), F.lit(0)).alias(f"q{i}") for i in (1, 2, 3, 4)])


QUERIES = {
    "star_join": star, "sweep_rollup": rollup, "sweep_cube": cube, "event_json_keys": event_json, "event_sessions": sessions, "index_version_asof": index_versions, "label_pivot": label_neighbours,
    "doc_vectors": vector_table("doc"), "order_vectors": vector_table("order"), "event_vectors": vector_table("event"), **{f"events_{k}": event_windows(k) for k in ("tumbling", "sliding", "session")},
}

_SESSION = "SELECT *, sum(new) OVER (PARTITION BY {by} ORDER BY us, event_id) AS s FROM (SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY {by} ORDER BY us, event_id) {test} THEN 0 ELSE 1 END AS new FROM (SELECT *, epoch_us(ts) AS us FROM events))"
_SCALED = "SELECT {key} AS vec_id, slot::BIGINT AS slot, round((v - avg(v) OVER (PARTITION BY slot)) / CASE WHEN stddev_samp(v) OVER (PARTITION BY slot) > 0 THEN stddev_samp(v) OVER (PARTITION BY slot) ELSE 1 END, 4) AS value FROM (SELECT {key}, unnest(vs) AS v, generate_subscripts(vs, 1) - 1 AS slot FROM rows)"
SQL = {
    "star_join": "WITH p AS (SELECT l_orderkey, sum(l_extendedprice * (1 - l_discount)) AS paid FROM lineitem GROUP BY 1) SELECT r_name, n_name, count(*) AS orders, round(sum(paid), 2) AS revenue FROM p JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL",
    "sweep_rollup": "SELECT o_orderstatus, o_orderpriority, count(*) AS n, round(avg(o_totalprice), 2) AS mean_total, grouping(o_orderstatus, o_orderpriority)::BIGINT AS level FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)",
    "sweep_cube": "SELECT lang, source, count(*) AS n, sum(n_chars)::BIGINT AS chars, grouping(lang, source)::BIGINT AS level FROM documents GROUP BY CUBE (lang, source) HAVING count(*) >= 5",
    "event_json_keys": "SELECT event_type, key, count(*) AS n FROM (SELECT event_type, unnest(json_keys(props)) AS key FROM events) GROUP BY ALL",
    "event_sessions": f"SELECT user_id, s::BIGINT AS session, count(*) AS n, max(us) - min(us) AS length_us FROM ({_SESSION.format(by='user_id', test='<= 1800000000')}) GROUP BY ALL",
    "index_version_asof": "SELECT event_id, coalesce((SELECT arg_max(v.event_id, (epoch_us(v.ts), v.event_id)) FROM events v WHERE v.event_type = 'purchase' AND epoch_us(v.ts) <= epoch_us(e.ts)), -1) AS version FROM events e",
    "label_pivot": "SELECT label::BIGINT AS label, " + ", ".join(f"count(*) FILTER (q = {i}) AS q{i}" for i in (1, 2, 3, 4)) + " FROM (SELECT label, greatest(1, least(4, floor((embedding[1]::DOUBLE + 0.2::DOUBLE) / 0.1::DOUBLE)::INT + 1)) AS q FROM embeddings) GROUP BY label",
    "events_tumbling": "SELECT us - us % 300000000 AS start_us, us - us % 300000000 + 300000000 AS end_us, event_type, count(*) AS n, round(sum(value), 2) AS total FROM (SELECT *, epoch_us(ts) AS us FROM events) GROUP BY ALL",
    "events_sliding": "SELECT us - us % 300000000 - k * 300000000 AS start_us, us - us % 300000000 - k * 300000000 + 600000000 AS end_us, event_type, count(*) AS n, round(sum(value), 2) AS total FROM (SELECT *, epoch_us(ts) AS us FROM events), range(0, 2) r(k) GROUP BY ALL",
    "events_session": f"SELECT min(us) AS start_us, max(us) + 600000000 AS end_us, event_type, count(*) AS n, round(sum(value), 2) AS total FROM ({_SESSION.format(by='event_type', test='< 600000000')}) GROUP BY event_type, s",
    "doc_vectors": r"""WITH w AS (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[ \t\n\x0B\f\r]+')) AS w FROM documents), h AS (SELECT doc_id, ('0x' || substr(md5(w), 1, 7))::BIGINT AS h FROM w WHERE w <> ''),
      c AS (SELECT doc_id, h % 64 AS slot, sum(CASE WHEN (h // 64) % 2 = 0 THEN 1.0 ELSE -1.0 END)::DOUBLE AS v FROM h GROUP BY ALL)
      SELECT vec_id, slot, value FROM (SELECT doc_id AS vec_id, slot, round(v / sqrt(sum(v * v) OVER (PARTITION BY doc_id)), 4) AS value FROM c) WHERE value <> 0""",
    "order_vectors": "WITH rows AS (SELECT l_orderkey, [count(*)::DOUBLE, sum(l_quantity), avg(l_extendedprice), sum(l_extendedprice), avg(l_discount), avg(l_tax), max(o_totalprice), avg(date_diff('day', o_orderdate::DATE, l_shipdate::DATE)::DOUBLE)] AS vs FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY l_orderkey) SELECT * FROM (" + _SCALED.format(key="l_orderkey") + ") WHERE value <> 0",
    "event_vectors": "WITH kinds AS (SELECT DISTINCT event_type AS k FROM events), per AS (SELECT u.user_id, k, count(e.event_id)::DOUBLE AS n, coalesce(avg(value), 0) AS v FROM (SELECT DISTINCT user_id FROM events) u CROSS JOIN kinds LEFT JOIN events e ON e.user_id = u.user_id AND e.event_type = k GROUP BY ALL), rows AS (SELECT user_id, list_concat(list(n ORDER BY k), list(v ORDER BY k)) AS vs FROM per GROUP BY user_id) SELECT * FROM (" + _SCALED.format(key="user_id") + ") WHERE value <> 0",
}
