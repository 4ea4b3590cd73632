"""Selections, scan strategies and kernels, predicate placement, dimensions, relational probes, joins."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators.joins import nested_loop_join, self_pairs, vector_range_join, vector_topk_join
from ..measures.reads import reads
from ..operators.relational import cents, relational_scan_sum, sorted_copy, store_indexed, stored_probe_sum
from ..operators.scan import (
    collect_queries, phase_times, scan, scan_sparse, scan_split, select_bound, select_product, select_unrolled,
)
from ..sources.stored import stored
from ..sources.tables import LADDER, first_components, ingest, sparsified, tile, widen
from .registry import CARRIER_EVENTS, MIX, U6, V, query, sql_bound, sql_cos, sql_queries, sql_topk, u6


def block(c, b):
    return collect_queries(c.queries(b))


def first_vector(c):
    return block(c, 1).matrix[0].tolist()


PAIR = ("query_id", "vec_id")
ONE = "(SELECT embedding FROM embeddings WHERE vec_id = 0)"

# ---- selection algebra


@query("select_bound", f"SELECT vec_id, {U6.format('s')} AS score_u6 FROM (SELECT vec_id, {sql_cos('embedding', ONE)} AS s FROM embeddings) WHERE s > 0.2")
def _(c):
    return select_bound(c.embeddings, first_vector(c), "cosine", 0.2).select("vec_id", u6())


@query("select_cross_equiv", sql_bound(sql_queries(10), "embeddings", 0.3))
def _(c):
    return select_product(c.embeddings, c.queries(10), bound=0.3).select(*PAIR, u6())


CHEAP = "o_totalprice < 51000"
HALF = "o_totalprice < 251000"


@query("mixed_push", sql_bound(sql_queries(100), MIX, 0.2, cond=CHEAP))
def _(c):
    return scan(c.mix_orders(), block(c, 100), bound=0.2, cond=F.expr(CHEAP)).select(*PAIR, u6())


@query("mixed_no_push", sql_bound(sql_queries(100), MIX, 0.2, cond=CHEAP))
def _(c):
    return scan(c.mix_orders(), block(c, 100), bound=0.2, cond=F.expr(CHEAP), pushdown="none").select(*PAIR, u6())


# ---- kernels and strategies

ONE_EVENT = f"SELECT event_id, {U6.format('s')} AS score_u6 FROM (SELECT event_id, {sql_cos('embedding', ONE)} AS s FROM {CARRIER_EVENTS}) WHERE s > 0.3"


@query("range_loop_b1", ONE_EVENT)
def _(c):
    return select_bound(c.carrier_events(), first_vector(c), "cosine", 0.3).select("event_id", u6())


@query("range_unrolled_b1", ONE_EVENT)
def _(c):
    return select_unrolled(c.carrier_events(), first_vector(c), 0.3).select("event_id", u6())


@query("range_rowvec_b1", ONE_EVENT)
def _(c):
    return scan(c.carrier_events(), block(c, 1), "event_id", bound=0.3, strategy="pairwise").select("event_id", u6())


def sql_counts(queries: str, rows: str, bound: float) -> str:
    return f"SELECT query_id, count(*) AS n_matches FROM ({sql_bound(queries, rows, bound, 'event_id')}) GROUP BY query_id"


def counted(found):
    return found.groupBy("query_id").agg(F.count(F.lit(1)).alias("n_matches"))


@query("range_1_to_n", sql_counts(sql_queries(10), CARRIER_EVENTS, 0.3))
def _(c):
    return counted(scan(c.carrier_events(), block(c, 10), "event_id", bound=0.3, strategy="block_rows"))


@query("range_n_to_1", sql_counts(sql_queries(10), CARRIER_EVENTS, 0.3))
def _(c):
    return counted(scan(c.carrier_events(), block(c, 10), "event_id", bound=0.3, strategy="block_queries"))


@query("range_gemm_b100", sql_bound(sql_queries(100), "embeddings", 0.3))
def _(c):
    return scan(c.embeddings, block(c, 100), bound=0.3).select(*PAIR, u6())


@query("range_gemm_all", sql_bound(sql_queries(1 << 30), "embeddings", 0.3))
def _(c):
    return vector_range_join(c.embeddings, c.embeddings, 0.3).select(F.col("l_id").alias("query_id"), F.col("r_id").alias("vec_id"), u6())


@query("range_thr09_selfmatch", f"SELECT query_id, vec_id FROM ({sql_bound(sql_queries(1 << 30), 'embeddings', 0.9)})")
def _(c):
    return vector_range_join(c.embeddings, c.embeddings, 0.9).select(F.col("l_id").alias("query_id"), F.col("r_id").alias("vec_id"))


# ---- predicate placement

MIXED_10 = sql_bound(sql_queries(10), MIX, 0.2, cond=HALF)


@query("inline_filter", MIXED_10)
def _(c):
    return scan(c.mix_orders(), block(c, 10), bound=0.2, cond=F.expr(HALF), strategy="block_queries", pushdown="inline").select(*PAIR, u6())


@query("late_materialise", MIXED_10)
def _(c):
    return scan(c.mix_orders(), block(c, 10), bound=0.2, cond=F.expr(HALF), pushdown="late").select(*PAIR, u6())


@query("late_split_storage", MIXED_10)
def _(c):
    attributes = c.orders.select(F.col("o_orderkey").alias("vec_id"), "o_totalprice")
    return scan_split(attributes, c.embeddings, block(c, 10), F.expr(HALF), bound=0.2).select(*PAIR, u6())


@query("minibatch_filter", MIXED_10)
def _(c):
    return scan(c.mix_orders(), block(c, 10), bound=0.2, cond=F.expr(HALF), pushdown="minibatch", batch_rows=64).select(*PAIR, u6())


@query(
    "sparse_scan",
    f"""WITH z AS (SELECT vec_id, list_transform({V.format('embedding')}, lambda x: CASE WHEN abs(x) < 0.05 THEN 0 ELSE x END) AS v FROM embeddings)
SELECT vec_id, {U6.format('s')} AS score_u6 FROM (SELECT vec_id, list_dot_product(v, (SELECT v FROM z WHERE vec_id = 0)) AS s FROM z) WHERE s > 0.2""",
)
def _(c):
    q = {i: x for i, x in enumerate(first_vector(c)) if abs(x) >= 0.05}
    rows = c.embeddings.select("vec_id", sparsified("embedding", 0.05).alias("sparse"))
    return scan_sparse(rows, q, 0.2).select("vec_id", u6())


# ---- top-k


@query("topk10_one", f"SELECT rank, vec_id, score_u6 FROM ({sql_topk(sql_queries(1), 'embeddings', 10)})")
def _(c):
    return scan(c.embeddings, block(c, 1), k=10).select("rank", "vec_id", u6())


@query("topk64_batch", sql_topk(sql_queries(100), "embeddings", 64))
def _(c):
    return scan(c.embeddings, block(c, 100), k=64).select("query_id", "rank", "vec_id", u6())


def _ladder_topk(percent: int) -> None:
    cond = f"o_totalprice < {LADDER[percent]}"

    @query(f"topk_filtered_{percent}", sql_topk(sql_queries(10), MIX, 10, cond))
    def _(c):
        return scan(c.mix_orders(), block(c, 10), k=10, cond=F.expr(cond)).select("query_id", "rank", "vec_id", u6())


for _percent in (1, 10, 50, 90):
    _ladder_topk(_percent)

_LISTS = {
    "ip": (f"list_dot_product({V.format('r.embedding')}, {V.format('q.qvec')})", "DESC"),
    "l2": (f"list_distance({V.format('r.embedding')}, {V.format('q.qvec')})", "ASC"),
    "l1": (f"list_sum(list_transform(list_zip({V.format('r.embedding')}, {V.format('q.qvec')}), lambda p: abs(p[1] - p[2])))", "ASC"),
    "linf": (f"list_max(list_transform(list_zip({V.format('r.embedding')}, {V.format('q.qvec')}), lambda p: abs(p[1] - p[2])))", "ASC"),
    "cosine_distance": (f"list_cosine_distance({V.format('r.embedding')}, {V.format('q.qvec')})", "ASC"),
    "sign_hamming": (
        f"CAST(len(list_filter(list_zip({V.format('r.embedding')}, {V.format('q.qvec')}), lambda p: (p[1] < 0) <> (p[2] < 0))) AS DOUBLE)",
        "ASC",
    ),
}


def _metric_topk(name: str, score: str, order: str) -> None:
    @query(f"topk_{name}", sql_topk(sql_queries(10), "embeddings", 10, score=score, desc=order))
    def _(c):
        return scan(c.embeddings, block(c, 10), k=10, metric=name).select("query_id", "rank", "vec_id", u6())


for _name, (_score, _order) in _LISTS.items():
    _metric_topk(_name, _score, _order)

# ---- dimensions


@query(
    "tile_invariance",
    " UNION ALL ".join(f"SELECT {r} AS r, query_id, rank, vec_id FROM ({sql_topk(sql_queries(10), 'embeddings', 10)})" for r in (4, 16)),
)
def _(c):
    def one(r):
        rows = c.embeddings.withColumn("embedding", tile("embedding", r))
        q = collect_queries(c.queries(10).withColumn("qvec", tile("qvec", r)))
        return scan(rows, q, k=10).select(F.lit(r).alias("r"), "query_id", "rank", "vec_id")

    return one(4).unionByName(one(16))


def sql_widen(r: int) -> str:
    n = "(SELECT count(*) FROM embeddings)"
    parts = ", ".join(f"(SELECT x.embedding FROM embeddings x WHERE x.vec_id = (e.vec_id + {j}) % {n})" for j in range(r))
    return f"(SELECT e.vec_id, list_transform(flatten([{parts}]), lambda v: CAST(v AS DOUBLE) / sqrt({r})) AS embedding FROM embeddings e)"


def _widen_counts(r: int, bound: float) -> None:
    sql = f"""WITH w AS MATERIALIZED {sql_widen(r)}
SELECT query_id, count(*) AS n_matches FROM ({sql_bound('SELECT vec_id AS query_id, embedding AS qvec FROM w WHERE vec_id < 10', 'w', bound)}) GROUP BY query_id"""

    @query(f"widen{64 * r}_counts", sql)
    def _(c):
        rows = widen(c.embeddings, r)
        q = collect_queries(rows.where("vec_id < 10").select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("qvec")))
        return counted(scan(rows, q, bound=bound))


_widen_counts(4, 0.1)
_widen_counts(16, 0.05)


@query(
    "slice32_topk",
    sql_topk("SELECT vec_id AS query_id, embedding[1:32] AS qvec FROM embeddings WHERE vec_id < 10", "(SELECT vec_id, embedding[1:32] AS embedding FROM embeddings)", 10),
)
def _(c):
    rows = c.embeddings.withColumn("embedding", first_components("embedding", 32))
    q = collect_queries(c.queries(10).withColumn("qvec", first_components("qvec", 32)))
    return scan(rows, q, k=10).select("query_id", "rank", "vec_id", u6())


# ---- ladders and counted work


def _ladder_union(f):
    out = None
    for percent, bound in LADDER.items():
        one = f(bound).select(F.lit(bound).alias("bound"), "*")
        out = one if out is None else out.unionByName(one)
    return out


def sql_ladder(b: int) -> str:
    return " UNION ALL ".join(
        f"SELECT {bound} AS bound, count(*) AS n_pairs FROM ({sql_bound(sql_queries(b), MIX, 0.2, cond=f'o_totalprice < {bound}')})"
        for bound in LADDER.values()
    )


def _ladder_counts(name: str, b: int) -> None:
    @query(name, sql_ladder(b))
    def _(c):
        # one scan for all bounds: pairs are found once and counted under each
        q = block(c, b)
        rows = c.mix_orders()
        found = scan(rows, q, bound=0.2).join(rows.select("vec_id", "o_totalprice"), "vec_id")
        bounds = F.explode(F.array(*[F.lit(x) for x in LADDER.values()]))
        each = found.withColumn("bound", bounds).groupBy("bound").agg(F.count_if(F.col("o_totalprice") < F.col("bound")).alias("n_pairs"))
        return each


_ladder_counts("ladder_counts_b1", 1)
_ladder_counts("ladder_counts_batch", 100)

# a batch of 10,000 requests, which repeat the vectors
SQL_REQUESTS = f"SELECT event_id AS query_id, embedding AS qvec FROM {CARRIER_EVENTS} WHERE event_id < 10000"


@query(
    "ladder_counts_10k",
    f"""SELECT bound, count(*) FILTER (o_totalprice < bound) AS n_pairs
FROM (SELECT r.o_totalprice, {sql_cos('r.embedding', 'q.qvec')} AS s FROM ({SQL_REQUESTS}) q CROSS JOIN (SELECT * FROM {MIX}) r)
CROSS JOIN (SELECT unnest({list(LADDER.values())}) AS bound) WHERE s > 0.2 GROUP BY bound""",
)
def _(c):
    """The ladder for a batch of 10,000: one matrix product a block; counts leave the tasks, not pairs."""
    q = collect_queries(c.request_queries(10_000))
    found = scan(c.mix_orders().select("vec_id", "embedding"), q, bound=0.2).groupBy("vec_id").count()
    priced = found.join(c.orders.select(F.col("o_orderkey").alias("vec_id"), "o_totalprice"), "vec_id")
    bounds = F.explode(F.array(*[F.lit(x) for x in LADDER.values()]))
    return priced.withColumn("bound", bounds).groupBy("bound").agg(
        F.coalesce(F.sum(F.when(F.col("o_totalprice") < F.col("bound"), F.col("count"))), F.lit(0)).alias("n_pairs")
    )


@query(
    "range_gemm_b10k",
    f"SELECT query_id, count(*) AS n FROM ({sql_bound(SQL_REQUESTS, 'embeddings', 0.3)}) GROUP BY query_id",
)
def _(c):
    q = collect_queries(c.request_queries(10_000))
    return scan(c.embeddings, q, bound=0.3).groupBy("query_id").agg(F.count(F.lit(1)).alias("n"))


@query(
    "dim_batch_grid",
    " UNION ALL ".join(
        f"""SELECT {d} AS d, {b} AS b, (SELECT count(*) FROM ({sql_bound(sql_queries(b) if b <= 100 else SQL_REQUESTS, 'embeddings', 0.3)})) AS n_pairs"""
        for d in (64, 256, 1024)
        for b in (1, 100, 10_000)
    ),
)
def _(c):
    """Pairs within the bound for each dimension and batch size; repeated components leave cosines as they are."""
    out = None
    for d in (64, 256, 1024):
        rows = c.embeddings.select("vec_id", tile("embedding", d // 64).alias("embedding"))
        for b in (1, 100, 10_000):
            asked = c.queries(b) if b <= 100 else c.request_queries(b)
            q = collect_queries(asked.select("query_id", tile("qvec", d // 64).alias("qvec")), max_bytes=128 << 20)
            one = scan(rows, q, bound=0.3).agg(F.count(F.lit(1)).alias("n_pairs")).select(F.lit(d).alias("d"), F.lit(b).alias("b"), "n_pairs")
            out = one if out is None else out.unionByName(one)
    return out


@query(
    "scan_distance_counts",
    " UNION ALL ".join(f"SELECT {x} AS bound, 100 * count(*) AS evals FROM {MIX} WHERE o_totalprice < {x}" for x in LADDER.values()),
)
def _(c):
    return _ladder_union(lambda x: c.mix_orders().where(F.col("o_totalprice") < x).agg((F.count(F.lit(1)) * 100).alias("evals")))


@query(
    "selectivity_exact",
    " UNION ALL ".join(f"SELECT {x} AS bound, count(*) FILTER (o_totalprice < {x}) AS n, CAST(round(1000000.0 * count(*) FILTER (o_totalprice < {x}) / count(*)) AS BIGINT) AS fraction_u6 FROM {MIX}" for x in LADDER.values()),
)
def _(c):
    n = lambda x: F.count_if(F.col("o_totalprice") < x)
    return _ladder_union(
        lambda x: c.mix_orders().agg(n(x).alias("n"), F.round(1_000_000 * n(x) / F.count(F.lit(1))).cast("long").alias("fraction_u6"))
    )


GRID = [(d, b, percent) for d in (64, 1024) for b in (1, 100, 10_000) for percent in (10, 90)]


@query(
    "phase_grid",
    " UNION ALL ".join(
        f"SELECT {d} AS d, {b} AS b, {percent} AS percent, count(*) AS n_rows, 3 AS n_phases, 100 AS share_sum FROM {MIX} WHERE o_totalprice < {LADDER[percent]}"
        for d, b, percent in GRID
    ),
)
def _(c):
    """Phases of the matrix scan for each cell of dimension, batch and percentage; their shares add up."""
    out = None
    for d, b, percent in GRID:
        rows = c.mix_orders().select("o_totalprice", tile("embedding", d // 64).alias("embedding"))
        asked = c.queries(b) if b <= 100 else c.request_queries(b)
        q = collect_queries(asked.select("query_id", tile("qvec", d // 64).alias("qvec")), max_bytes=128 << 20)
        got = phase_times(rows, q, F.col("o_totalprice") < LADDER[percent])
        one = got.agg(F.max("n_rows").alias("n_rows"), F.count(F.lit(1)).cast("int").alias("n_phases"), F.round(F.sum("share")).cast("int").alias("share_sum"))
        one = one.select(F.lit(d).alias("d"), F.lit(b).alias("b"), F.lit(percent).alias("percent"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@query("ingest_unit_topk", sql_topk(sql_queries(10), "embeddings", 10))
def _(c):
    """Vectors normalised when they come in: the inner product of what is stored is the cosine."""
    path = stored(c.spark, "unit-embeddings", c.sf_dir, lambda p: ingest(c.embeddings).write.mode("overwrite").parquet(p))
    rows = c.spark.read.parquet(path)
    q = collect_queries(rows.where("vec_id < 10").select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("qvec")))
    return scan(rows, q, metric="ip", k=10).select("query_id", "rank", "vec_id", u6())


@query("ingest_norms", f"SELECT vec_id, {U6.format('sqrt(list_dot_product(CAST(embedding AS DOUBLE[]), CAST(embedding AS DOUBLE[])))')} AS norm_u6 FROM embeddings")
def _(c):
    return ingest(c.embeddings).select("vec_id", F.round(F.col("norm") * 1_000_000).cast("long").alias("norm_u6"))


@query("phase_shares")
def _(c):
    return phase_times(c.mix_orders(), block(c, 100), F.expr(HALF))


# ---- relational scan and probe

# Bounds on l_extendedprice that keep about so many percent of the rows.
PRICE = {
    0.01: 910.4, 0.05: 952, 0.1: 1004, 0.5: 1420, 1: 1950, 5: 6105, 10: 11350, 25: 26925, 50: 52900, 75: 78975, 90: 94600, 95: 99795, 99: 103959,
}
ROW = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice"]


def sql_sum(cond: str) -> str:
    return f"SELECT count(*) AS n, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS sum_cents FROM lineitem WHERE {cond}"


def indexed_lineitem(c, key: str = "l_extendedprice", kind: str = "tree") -> str:
    """Path of line items stored by page with an index on ``key``; built once, before any probe."""
    return stored(c.spark, f"lineitem-{key}-{kind}", c.sf_dir, lambda path: store_indexed(c.lineitem, path, key, ROW, kind=kind))


def clustered_lineitem(c):
    write = lambda path: sorted_copy(c.lineitem, "l_extendedprice", ["l_extendedprice"]).write.mode("overwrite").parquet(path)
    return c.spark.read.parquet(stored(c.spark, "lineitem-clustered", c.sf_dir, write))


def by_scan(c, hi: float, one_task: bool = False):
    return relational_scan_sum(c.lineitem, "l_extendedprice", hi, "l_extendedprice", one_task)


def by_probe(c, hi: float, one_task: bool = False):
    return stored_probe_sum(c.spark, indexed_lineitem(c), "l_extendedprice", F.col("l_extendedprice") < hi, ROW, "l_extendedprice", one_task)


def by_clustered(c, hi: float, one_task: bool = False):
    return relational_scan_sum(clustered_lineitem(c), "l_extendedprice", hi, "l_extendedprice", one_task)


RELATIONAL = {"scan": by_scan, "probe": by_probe, "clustered": by_clustered}


def _relational(percent: float, hi: float) -> None:
    label = f"{percent:g}".replace(".", "p")
    for path, run in RELATIONAL.items():
        query(f"rel_{path}_sum_{label}", sql_sum(f"l_extendedprice < {hi}"))(lambda c, run=run: run(c, hi))


for _percent, _hi in PRICE.items():
    _relational(_percent, _hi)
for _path, _run in RELATIONAL.items():
    query(f"rel_{_path}_one_task", sql_sum(f"l_extendedprice < {PRICE[1]}"))(lambda c, run=_run: run(c, PRICE[1], True))


@query(
    "rel_reads",
    "SELECT * FROM (VALUES ('clustered', 1, TRUE), ('clustered', 50, TRUE), ('clustered', 99, FALSE), ('probe', 0, TRUE), ('probe', 50, FALSE)) "
    "t(path, percent, reads_less)",
)
def _(c):
    """Whether a probe reads fewer rows from files than the scan: a clustered copy does while few qualify, a secondary index only for a row or so in 10,000."""
    rows = []
    for path, percent in (("clustered", 1), ("clustered", 50), ("clustered", 99), ("probe", 0.01), ("probe", 50)):
        hi = PRICE[percent]
        probe, scanned = reads(RELATIONAL[path](c, hi)), reads(by_scan(c, hi))
        rows.append((path, int(percent), probe["rows"] < scanned["rows"]))
    return c.spark.createDataFrame(rows, "path string, percent int, reads_less boolean")


@query("rel_point", sql_sum("l_partkey = 7"))
def _(c):
    path = indexed_lineitem(c, "l_partkey", "hash")
    return stored_probe_sum(c.spark, path, "l_partkey", F.col("l_partkey") == 7, ROW, "l_extendedprice")


@query("rel_point_scan", sql_sum("l_partkey = 7"))
def _(c):
    return c.lineitem.where("l_partkey = 7").agg(F.count(F.lit(1)).alias("n"), cents("l_extendedprice"))


# ---- joins


def sql_join(l_cond: str, r_cond: str, bound: float, on: str = "TRUE", left: str = "embeddings") -> str:
    return f"""SELECT l_id, r_id, {U6.format('s')} AS score_u6
FROM (SELECT l.vec_id AS l_id, r.vec_id AS r_id, {sql_cos('l.embedding', 'r.embedding')} AS s
      FROM (SELECT * FROM {left} WHERE {l_cond}) l JOIN (SELECT * FROM embeddings WHERE {r_cond}) r ON {on}) WHERE s > {bound}"""


def joined(out):
    return out.select("l_id", "r_id", u6())


@query("vec_join_bound", sql_join("label = 0", "label = 1", 0.25))
def _(c):
    return joined(vector_range_join(c.embeddings, c.embeddings, 0.25, l_cond=F.expr("label = 0"), r_cond=F.expr("label = 1"), block_rows=40))


@query("nested_loop_join", sql_join("label = 0", "label = 1", 0.25))
def _(c):
    return joined(nested_loop_join(c.embeddings.where("label = 0"), c.embeddings.where("label = 1"), 0.25))


@query("vec_self_pairs", sql_join("TRUE", "TRUE", 0.35, "l.vec_id < r.vec_id"))
def _(c):
    return joined(self_pairs(c.embeddings, 0.35, block_rows=200))


SQL_JOIN_TOPK = f"""SELECT query_id AS l_id, rank, vec_id AS r_id FROM ({sql_topk('SELECT vec_id AS query_id, embedding AS qvec FROM embeddings WHERE label = 0', 'embeddings', 5, 'label = 1')})"""


@query("vec_join_topk", SQL_JOIN_TOPK)
def _(c):
    return vector_topk_join(c.embeddings, c.embeddings, 5, l_cond=F.expr("label = 0"), r_cond=F.expr("label = 1"), block_rows=40).select("l_id", "rank", "r_id")


# ---- use cases

GEO = """embeddings JOIN orders ON vec_id = o_orderkey JOIN customer ON o_custkey = c_custkey
  JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"""
PLACE_DATE = "r_name = 'EUROPE' AND o_orderdate >= TIMESTAMP '1997-01-01' AND o_orderdate < TIMESTAMP '1999-01-01'"


@query(
    "geo_date_topk",
    f"SELECT t.rank, t.vec_id, g.n_name, t.score_u6 FROM ({sql_topk(sql_queries(1), GEO, 10, PLACE_DATE)}) t JOIN (SELECT vec_id, n_name FROM {GEO}) g USING (vec_id)",
)
def _(c):
    geo = c.mix_geo().where(
        (F.col("r_name") == "EUROPE") & (F.col("o_orderdate") >= F.lit("1997-01-01").cast("timestamp_ntz")) & (F.col("o_orderdate") < F.lit("1999-01-01").cast("timestamp_ntz"))
    )
    return scan(geo, block(c, 1), k=10).join(geo.select("vec_id", "n_name"), "vec_id").select("rank", "vec_id", "n_name", u6())


DOCS = "embeddings JOIN documents ON vec_id = doc_id"


@query(
    "tagged_topk",
    f"SELECT t.query_id, t.rank, t.vec_id, d.source, t.score_u6 FROM ({sql_topk(sql_queries(5), DOCS, 10, 'lang = ' + chr(39) + 'en' + chr(39))}) t JOIN documents d ON d.doc_id = t.vec_id",
)
def _(c):
    found = scan(c.mix_documents(), block(c, 5), k=10, cond=F.col("lang") == "en")
    return found.join(c.documents.select(F.col("doc_id").alias("vec_id"), "source"), "vec_id").select("query_id", "rank", "vec_id", "source", u6())


@query("flagged_neighbours", sql_join("toxic = 1", "TRUE", 0.25, left="(SELECT e.*, b.toxic FROM embeddings e JOIN labels b ON e.vec_id = b.doc_id JOIN documents d ON d.doc_id = e.vec_id)"))
def _(c):
    return joined(vector_range_join(c.mix_documents(), c.embeddings, 0.25, l_cond=F.col("toxic") == 1))


