"""Operators around the methods: aggregates, windows, joins, set operations, functions, SQL."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.aggregates import centroid_positions
from ..functions.sql import cosine_to, register, vec_mean
from ..operators.scan import scan, select_bound
from .registry import CARRIER_EVENTS, MIX, ORACLES, U6, query, sql_bound, sql_cos, sql_queries, u6
from .scans import ONE, block, first_vector


@query(
    "centroids_by_label",
    f"""SELECT label, CAST(pos - 1 AS INTEGER) AS pos, {U6.format('avg(x)')} AS mean_u6
FROM (SELECT label, unnest(CAST(embedding AS DOUBLE[])) AS x, unnest(range(1, len(embedding) + 1)) AS pos FROM embeddings) GROUP BY label, pos""",
)
def _(c):
    return centroid_positions(c.embeddings, "label").select("label", "pos", u6("mean").alias("mean_u6"))


# ---- grouped match counts

MATCHES = f"(SELECT m.query_id, d.lang, d.source FROM ({sql_bound(sql_queries(20), 'embeddings', 0.2)}) m JOIN documents d ON d.doc_id = m.vec_id)"


def matches(c):
    docs = c.documents.select(F.col("doc_id").alias("vec_id"), "lang", "source")
    return scan(c.embeddings, block(c, 20), bound=0.2).join(docs, "vec_id")


def n():
    return F.count(F.lit(1)).alias("n")


@query("match_cube", f"SELECT lang, source, count(*) AS n FROM {MATCHES} GROUP BY CUBE (lang, source)")
def _(c):
    return matches(c).cube("lang", "source").agg(n())


@query("match_rollup", f"SELECT lang, source, count(*) AS n FROM {MATCHES} GROUP BY ROLLUP (lang, source)")
def _(c):
    return matches(c).rollup("lang", "source").agg(n())


@query("match_grouping_sets", f"SELECT lang, source, count(*) AS n FROM {MATCHES} GROUP BY GROUPING SETS ((lang), (source))")
def _(c):
    m = matches(c)
    return m.groupingSets([[F.col("lang")], [F.col("source")]], "lang", "source").agg(n())


@query(
    "match_pivot",
    f"""SELECT query_id, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'fr') AS fr FROM {MATCHES} GROUP BY query_id""",
)
def _(c):
    return matches(c).groupBy("query_id").pivot("lang", ["en", "fr"]).agg(F.count(F.lit(1))).fillna(0)


@query("distinct_matches", f"SELECT query_id, count(DISTINCT vec_id) AS n FROM ({sql_bound(sql_queries(20), CARRIER_EVENTS, 0.3, 'vec_id')}) GROUP BY query_id")
def _(c):
    found = scan(c.carrier_events(), block(c, 20), bound=0.3)
    return found.groupBy("query_id").agg(F.countDistinct("vec_id").alias("n"))


# ---- semi, anti, outer, as-of and interval joins

NEAR = f"(SELECT query_id, vec_id FROM ({sql_bound(sql_queries(100), 'embeddings', 0.35)}) WHERE query_id <> vec_id)"


def near(c):
    return scan(c.embeddings, block(c, 100), bound=0.35).where("query_id <> vec_id")


@query("anti_no_match", f"SELECT vec_id FROM embeddings WHERE vec_id < 100 AND vec_id NOT IN (SELECT query_id FROM {NEAR})")
def _(c):
    q = c.queries(100).select(F.col("query_id").alias("vec_id"))
    return q.join(near(c).select(F.col("query_id").alias("vec_id")), "vec_id", "left_anti")


@query("semi_candidates", f"SELECT vec_id FROM embeddings WHERE vec_id < 100 AND vec_id IN (SELECT query_id FROM {NEAR})")
def _(c):
    q = c.queries(100).select(F.col("query_id").alias("vec_id"))
    return q.join(near(c).select(F.col("query_id").alias("vec_id")), "vec_id", "left_semi")


@query("outer_topk", f"SELECT q.query_id, count(m.vec_id) AS n FROM ({sql_queries(100)}) q LEFT JOIN {NEAR} m USING (query_id) GROUP BY q.query_id")
def _(c):
    return c.queries(100).join(near(c), "query_id", "left").groupBy("query_id").agg(F.count("vec_id").alias("n"))


@query(
    "asof_event_order",
    "SELECT event_id, coalesce(lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id), -1) AS prev_id FROM events",
)
def _(c):
    """Latest earlier event of the same user (-1: none), without a join of all pairs."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return c.events.select("event_id", F.lag("event_id", 1, -1).over(w).alias("prev_id"))


@query(
    "interval_events",
    """SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) - 1 AS n FROM events""",
)
def _(c):
    """Other events of the user from one hour before up to the event's own time."""
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)
    return c.events.select("event_id", (F.count(F.lit(1)).over(w) - 1).alias("n"))


# ---- set operations, windows


@query("intersect_queries", f"""SELECT vec_id FROM ({sql_bound(sql_queries(10), 'embeddings', 0.15)}) WHERE query_id = 0
INTERSECT SELECT vec_id FROM ({sql_bound(sql_queries(10), 'embeddings', 0.15)}) WHERE query_id = 1""")  # fmt: skip
def _(c):
    found = scan(c.embeddings, block(c, 2), bound=0.15)
    return found.where("query_id = 0").select("vec_id").intersect(found.where("query_id = 1").select("vec_id"))


PRICES = f"(SELECT vec_id, label, CAST(round(o_totalprice * 100) AS BIGINT) AS price FROM {MIX})"


def prices(c):
    return c.mix_orders().select("vec_id", "label", F.round(F.col("o_totalprice") * 100).cast("long").alias("price"))


@query(
    "rank_functions",
    f"""SELECT vec_id, rank() OVER w AS rank, dense_rank() OVER w AS dense, CAST(ntile(4) OVER v AS INTEGER) AS quarter
FROM {PRICES} WINDOW w AS (PARTITION BY label ORDER BY price // 1000000), v AS (PARTITION BY label ORDER BY price, vec_id)""",
)
def _(c):
    w = Window.partitionBy("label").orderBy(F.floor(F.col("price") / 1_000_000))
    v = Window.partitionBy("label").orderBy("price", "vec_id")
    return prices(c).select("vec_id", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"), F.ntile(4).over(v).alias("quarter"))


@query(
    "running_matches",
    f"""SELECT query_id, vec_id, count(*) OVER (PARTITION BY query_id ORDER BY vec_id ROWS UNBOUNDED PRECEDING) AS so_far
FROM ({sql_bound(sql_queries(10), 'embeddings', 0.2)})""",
)
def _(c):
    w = Window.partitionBy("query_id").orderBy("vec_id").rowsBetween(Window.unboundedPreceding, 0)
    return scan(c.embeddings, block(c, 10), bound=0.2).select("query_id", "vec_id", F.count(F.lit(1)).over(w).alias("so_far"))


@query("selectivity_deciles", f"SELECT label, decile, count(*) AS n, CAST(max(price) AS BIGINT) AS most FROM (SELECT label, price, CAST(ntile(10) OVER (PARTITION BY label ORDER BY price, vec_id) AS INTEGER) AS decile FROM {PRICES}) GROUP BY label, decile")
def _(c):
    w = Window.partitionBy("label").orderBy("price", "vec_id")
    return prices(c).withColumn("decile", F.ntile(10).over(w)).groupBy("label", "decile").agg(n(), F.max("price").alias("most"))


# ---- functions


@query(
    "json_props_filter",
    f"SELECT event_id, {U6.format('s')} AS score_u6 FROM (SELECT event_id, {sql_cos('embedding', ONE)} AS s FROM {CARRIER_EVENTS} WHERE CAST(json_extract_string(props, '$.k') AS INTEGER) < 50) WHERE s > 0.3",
)
def _(c):
    k = F.from_json("props", "k int")["k"]
    return select_bound(c.carrier_events().where(k < 50), first_vector(c), "cosine", 0.3).select("event_id", u6())


@query(
    "string_date_functions",
    f"""SELECT CAST(year(o_orderdate) AS INTEGER) AS y, lower(substr(o_orderpriority, 1, 1)) AS p, count(*) AS n
FROM {MIX} WHERE o_orderpriority LIKE '%-%' AND o_orderdate BETWEEN TIMESTAMP '1993-01-01' AND TIMESTAMP '1997-12-31' GROUP BY 1, 2""",
)
def _(c):
    rows = c.mix_orders().where(
        F.col("o_orderpriority").like("%-%") & F.col("o_orderdate").between(F.lit("1993-01-01").cast("timestamp_ntz"), F.lit("1997-12-31").cast("timestamp_ntz"))
    )
    return rows.groupBy(F.year("o_orderdate").alias("y"), F.lower(F.substring("o_orderpriority", 1, 1)).alias("p")).agg(n())


@query(
    "map_array_functions",
    f"SELECT label, count(*) AS n, {U6.format('max(list_max(list_transform(CAST(embedding AS DOUBLE[]), lambda x: abs(x))))')} AS most_u6 FROM embeddings GROUP BY label",
)
def _(c):
    """Counts by label held as a map and unfolded, beside the largest absolute component."""
    largest = F.array_max(F.transform("embedding", lambda x: F.abs(x.cast("double"))))
    per = c.embeddings.groupBy("label").agg(n(), F.max(largest).alias("most"))
    held = per.select(F.map_from_arrays(F.array("label"), F.array("n")).alias("counts"), "most")
    return held.select(F.explode("counts").alias("label", "n"), "most").select("label", "n", u6("most").alias("most_u6"))


# ---- SQL


@query("sql_surface", f"SELECT vec_id, {U6.format('s')} AS score_u6 FROM (SELECT vec_id, {sql_cos('embedding', ONE)} AS s FROM embeddings) WHERE s > 0.2")
def _(c):
    register(c.spark)
    q = ", ".join(repr(x) + "D" for x in first_vector(c))
    return c.spark.sql(
        f"SELECT vec_id, CAST(round(s * 1000000) AS BIGINT) AS score_u6 FROM (SELECT vec_id, vec_cosine(embedding, array({q})) AS s FROM {{e}}) WHERE s > 0.2",
        e=c.embeddings,
    )


@query("udtf_topk", None)
def _(c):
    register(c.spark)
    q = ", ".join(repr(x) + "D" for x in first_vector(c))
    found = c.spark.sql(
        f"SELECT vec_id, score FROM vec_topk(TABLE(SELECT vec_id, embedding, vec_id % 8 AS part FROM {{e}}) PARTITION BY (part), array({q}), 10) ORDER BY score DESC, vec_id LIMIT 10",
        e=c.embeddings,
    )
    return found.select(F.row_number().over(Window.orderBy(F.col("score").desc(), "vec_id")).alias("rank"), "vec_id", u6())


def _oracle_of_udtf() -> None:
    from .registry import ORACLES

    ORACLES["udtf_topk"] = ORACLES["topk10_one"]


_oracle_of_udtf()


@query("udf_cosine", f"SELECT vec_id, {U6.format(sql_cos('embedding', ONE))} AS score_u6 FROM embeddings")
def _(c):
    """The cosine as a vectorised function over Arrow batches."""
    score = cosine_to(first_vector(c))
    return c.embeddings.select("vec_id", u6(score("embedding")))


@query("udaf_centroids", ORACLES["centroids_by_label"])
def _(c):
    """The same centroids by a grouped vectorised aggregate."""
    means = c.embeddings.groupBy("label").agg(vec_mean("embedding").alias("m"))
    return means.select("label", F.posexplode("m").alias("pos", "mean")).select("label", "pos", u6("mean").alias("mean_u6"))
