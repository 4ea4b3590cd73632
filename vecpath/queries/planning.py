"""Access-path selection over published cells and over the data."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import BooleanType, DoubleType, IntegerType, LongType, StringType, StructField, StructType

from ..api import search
from ..plans import planner, published
from ..sources.tables import LADDER
from .registry import MIX, query, sql_queries, sql_topk, u6
from .scans import CHEAP, block


def _values(rows: list[tuple]) -> str:
    quote = lambda v: f"'{v}'" if isinstance(v, str) else ("NULL" if v is None else str(v))
    return ", ".join("(" + ", ".join(map(quote, r)) + ")" for r in rows)


# ---- requests: every event asks for one search, whose kind follows from its columns

SOME = "CASE WHEN event_type IN ('view', 'click') THEN 1 ELSE 10000 END"
KERNEL_BATCH = "CASE event_type WHEN 'view' THEN 1 WHEN 'click' THEN 100 ELSE 10000 END"
PERCENTS = sorted({s for paths in published.CURVES.values() for ms in paths.values() for s in ms})


def turn(column: str, values) -> str:
    """SQL of both engines: the values in turn, by a whole number in a column."""
    values = list(values)
    at = f"((coalesce({column}, 0) % {len(values)}) + {len(values)}) % {len(values)}"
    return "CASE " + " ".join(f"WHEN {at} = {i} THEN {v}" for i, v in enumerate(values)) + " END"


def text(values) -> list[str]:
    return ["'" + v.replace("'", "''") + "'" for v in values]


CELL = {"s": turn("event_id", published.SCAN_PERCENT), "b": SOME, "d": turn("user_id", (64, 1024))}
CURVE_CELL = CELL | {"s": turn("event_id", PERCENTS)}
KERNEL_CELL = {"b": KERNEL_BATCH, "d": turn("user_id", (64, 256, 1024))}


def sql_asked(cell: dict[str, str]) -> str:
    """The requests of each cell and how many they are."""
    return f"SELECT {', '.join(cell)}, count(*) AS n_requests FROM (SELECT {', '.join(f'{e} AS {c}' for c, e in cell.items())} FROM events) GROUP BY {', '.join(cell)}"


def asked(c, cell: dict[str, str]):
    """The same in Spark."""
    escaped = lambda e: e.replace("''", "\\'")
    return c.events.select(*(F.expr(escaped(e)).alias(n) for n, e in cell.items())).groupBy(*cell).agg(F.count(F.lit(1)).alias("n_requests"))


def planned(cells, decide, schema: str):
    """``decide(row) -> rows``: the planner at work in the tasks, on every kind of request."""

    def work(batches):
        for batch in batches:
            rows = [r for cell in batch.to_pylist() for r in decide(cell)]
            if rows:
                names = [x.split()[0] for x in schema.split(", ")]
                yield pa.RecordBatch.from_pylist([dict(zip(names, r)) for r in rows], schema=to_arrow_schema(_parse(schema)))

    return cells.mapInArrow(work, schema)


def _parse(schema: str) -> StructType:
    kinds = {"int": IntegerType(), "long": LongType(), "double": DoubleType(), "string": StringType(), "boolean": BooleanType()}
    return StructType([StructField(name, kinds[kind]) for name, kind in (x.split() for x in schema.split(", "))])


INDEXED = planner.IndexInfo("cosine")


def _load(cell: dict) -> planner.Workload:
    return planner.Workload(1_000_000, cell["d"], cell["b"], cell["s"] / 100)


@query(
    "choose_kernel_grid",
    f"SELECT b, d, kernel, n_requests FROM (SELECT b, d, min_by(kernel, ms) AS kernel FROM (VALUES {_values(published.scan_rows())}) t(b, d, kernel, ms) GROUP BY b, d) JOIN ({sql_asked(KERNEL_CELL)}) USING (b, d)",
)
def _(c):
    """The kernel for the requests of each batch and dimension."""
    decide = lambda x: [(x["b"], x["d"], planner.choose_kernel(x["b"], x["d"]), x["n_requests"])]
    return planned(asked(c, KERNEL_CELL), decide, "b int, d int, kernel string, n_requests long")


SQL_CHEAPEST = f"""SELECT CAST(s AS INTEGER) AS s, b, d, path, n_requests
FROM (SELECT s, b, d, min_by(path, ms) AS path FROM (VALUES {_values(published.filter_rows())}) t(s, b, d, path, ms) GROUP BY s, b, d) JOIN ({sql_asked(CELL)}) USING (s, b, d)"""
PATH_OF_CELL = "s int, b int, d int, path string, n_requests long"


@query("choose_path_grid", SQL_CHEAPEST)
def _(c):
    """The planner's own choice for the requests, by its cost model, against the cheapest published cell."""
    decide = lambda x: [(x["s"], x["b"], x["d"], planner.choose_path(_load(x), INDEXED).path, x["n_requests"])]
    return planned(asked(c, CELL), decide, PATH_OF_CELL)


@query("advise_grid", SQL_CHEAPEST)
def _(c):
    decide = lambda x: [(x["s"], x["b"], x["d"], planner.advise_from_published(x["s"], x["d"], x["b"]), x["n_requests"])]
    return planned(asked(c, CELL), decide, PATH_OF_CELL)


def sql_cost(path: str, n: str, s: str, b: str, d: str, number=repr) -> str:
    """The cost of a path written as SQL: n rows, s the qualifying fraction, b the batch, d the dimension."""
    m = planner.default_model()
    if path == "scan":
        f, t, p = map(number, m.scan)
        return f"({n} / 1e6 * ({f} + pow({b}, 0.93) * {s} * ({t} + {d} * {p})))"
    if path == "matrix":
        a, c, e, g = map(number, m.matrix)
        return f"({n} / 1e6 * ({a} + {s} * {d} * {c} + {b} * {s} * ({e} + {d} * {g})))"
    g0, g1, g2, g3 = map(number, m.graph)
    return f"(exp({g0} + {g1} * ln({b}) + {g2} * ln({d}) - {g3} * ln({s})) * greatest(1.0, log2({n}) / 20))"


def double(x: float) -> str:
    """A number that SQL does not take for a decimal, whose products may overflow."""
    return f"CAST({x!r} AS DOUBLE)"


@query(
    "cost_model_grid",
    " UNION ALL ".join(
        f"SELECT CAST(s AS DOUBLE) AS s, b, d, path, CAST(ms AS DOUBLE) AS ms, CAST(round({sql_cost(p, '1000000.0', '(CAST(s AS DOUBLE) / 100)', 'b', 'd', double)} * 1000) AS BIGINT) AS modelled_us, n_requests "
        f"FROM (VALUES {_values(published.curve_rows())}) t(s, b, d, path, ms) JOIN ({sql_asked(CURVE_CELL)}) USING (s, b, d) WHERE path = '{p}'"
        for p in planner.PATHS
    ),
)
def _(c):
    """Modelled time for the requests at every published point."""

    def decide(x):
        model, curves = planner.default_model(), published.CURVES[x["b"], x["d"]]
        at = [(p, float(curves[p][x["s"]])) for p in planner.PATHS if x["s"] in curves[p]]
        return [(float(x["s"]), x["b"], x["d"], p, ms, round(1000 * model.cost(p, _load(x))), x["n_requests"]) for p, ms in at]

    return planned(asked(c, CURVE_CELL), decide, "s double, b int, d int, path string, ms double, modelled_us long, n_requests long")


@query(
    "adaptive_choices",
    f"""WITH f AS (SELECT bound, CAST(count(*) FILTER (o_totalprice < bound) AS DOUBLE) / count(*) AS s
  FROM {MIX} CROSS JOIN (SELECT unnest({list(LADDER.values())}) AS bound) GROUP BY bound),
w AS (SELECT bound, s, b, d FROM f CROSS JOIN (SELECT unnest([1, 100, 10000]) AS b) CROSS JOIN (SELECT unnest([64, 1024]) AS d)),
t AS ({' UNION ALL '.join(f"SELECT bound, b, d, '{p}' AS path, {sql_cost(p, '1000000.0', 'greatest(s, 1e-6)', 'b', 'd')} AS ms FROM w" for p in planner.PATHS)})
SELECT bound, b, d, min_by(path, ms) AS path FROM t GROUP BY bound, b, d""",
)
def _(c):
    """The path chosen for a million such rows from the selectivity of the data: each of the three wins somewhere."""
    model, info, rows = planner.Adaptive(), planner.IndexInfo("cosine"), []
    data = c.mix_orders().select("o_totalprice")
    for bound in LADDER.values():
        s = planner.selectivity(data, F.col("o_totalprice") < bound)
        for b in (1, 100, 10_000):
            for d in (64, 1024):
                w = planner.Workload(1_000_000, d, b, s)
                rows.append((bound, b, d, planner.choose_path(w, info, model.model).path))
    return c.spark.createDataFrame(rows, "bound int, b int, d int, path string")


SQL_MEASURED = f"SELECT t.*, n_requests FROM (VALUES {_values(published.filter_rows())}) t(s, b, d, path, ms) JOIN ({sql_asked(CELL)}) USING (s, b, d)"


def measured(c):
    """(s, b, d, path, ms, n_requests): the published times of what is asked for."""
    times = c.spark.createDataFrame(published.filter_rows(), "s double, b int, d int, path string, ms double")
    return asked(c, CELL).withColumn("s", F.col("s").cast("double")).join(F.broadcast(times), ["s", "b", "d"])


@query(
    "crossover_points",
    f"""WITH t AS ({SQL_MEASURED})
SELECT o.b, o.d, o.path, CAST(min(o.s) AS INTEGER) AS s, CAST(sum(o.n_requests) AS BIGINT) AS n_requests
FROM t o JOIN t g USING (s, b, d) WHERE o.path <> 'graph' AND g.path = 'graph' AND g.ms < o.ms GROUP BY o.b, o.d, o.path""",
)
def _(c):
    """First percentage asked for at which the graph is cheaper than each scan, and the requests for which it is."""
    rows = measured(c)
    graph = rows.where("path = 'graph'").select("s", "b", "d", F.col("ms").alias("graph"))
    cheaper = rows.where("path <> 'graph'").join(graph, ["s", "b", "d"]).where("graph < ms")
    return cheaper.groupBy("b", "d", "path").agg(F.min("s").cast("int").alias("s"), F.sum("n_requests").alias("n_requests"))


@query(
    "crossover_interpolated",
    f"""WITH t AS ({SQL_MEASURED}),
w AS (SELECT o.b, o.d, o.path, o.n_requests, ln(o.s) AS x, ln(g.ms) - ln(o.ms) AS diff
      FROM t o JOIN t g USING (s, b, d) WHERE o.path <> 'graph' AND g.path = 'graph'),
l AS (SELECT *, lag(x) OVER p AS x0, lag(diff) OVER p AS d0, sum(n_requests) OVER (PARTITION BY b, d, path) AS n FROM w WINDOW p AS (PARTITION BY b, d, path ORDER BY x))
SELECT b, d, path, CAST(round(1000 * min(exp(x0 + (x - x0) * d0 / (d0 - diff)))) AS BIGINT) AS permille10, CAST(max(n) AS BIGINT) AS n_requests FROM l WHERE d0 * diff < 0 GROUP BY b, d, path""",
)
def _(c):
    """Percentage at which the graph becomes cheaper than each scan, in thousandths, between the points asked for; and how many ask."""
    cells = measured(c).groupBy("b", "d").agg(
        F.array_sort(F.collect_list(F.struct("s", "path", "ms"))).alias("points"), F.sum(F.when(F.col("path") == "graph", F.col("n_requests"))).alias("n_requests")
    )

    def decide(x):
        line = lambda path: [p["ms"] for p in x["points"] if p["path"] == path]
        at = {o: planner.crossover([p["s"] for p in x["points"] if p["path"] == "graph"], line("graph"), line(o)) for o in ("scan", "matrix")}
        return [(x["b"], x["d"], other, round(1000 * p), x["n_requests"]) for other, p in at.items() if p is not None]

    return planned(cells, decide, "b int, d int, path string, permille10 long, n_requests long")


REQUESTS = [
    ("top-k by ip", planner.Workload(1_000_000, 64, 1, 0.9, 10, "ip"), planner.IndexInfo("ip")),
    ("top-k by l2", planner.Workload(1_000_000, 64, 1, 0.9, 10, "l2"), planner.IndexInfo("ip")),
    ("range by ip", planner.Workload(1_000_000, 64, 1, 0.9, None, "ip"), planner.IndexInfo("ip")),
    ("exact top-k", planner.Workload(1_000_000, 64, 1, 0.9, 10, "ip", 1.0), planner.IndexInfo("ip")),
    ("no index", planner.Workload(1_000_000, 64, 1, 0.9, 10, "ip"), planner.IndexInfo()),
    ("few qualify", planner.Workload(1_000_000, 64, 1, 0.01, 10, "ip"), planner.IndexInfo("ip")),
    ("few qualify, large batch", planner.Workload(1_000_000, 64, 10_000, 0.01, 10, "ip"), planner.IndexInfo("ip")),
]
EXPECTED = [
    ("top-k by ip", "graph", "cheapest"),
    ("top-k by l2", "scan", "metric differs from the index"),
    ("range by ip", "scan", "range search"),
    ("exact top-k", "scan", "exact result"),
    ("no index", "scan", "no index"),
    ("few qualify", "scan", "cheapest"),
    ("few qualify, large batch", "matrix", "cheapest"),
]


KIND = {"request": turn("event_id", text(name for name, *_ in REQUESTS))}


@query("fallback_reason_table", f"SELECT t.*, n_requests FROM (VALUES {_values(EXPECTED)}) t(request, path, reason) JOIN ({sql_asked(KIND)}) USING (request)")
def _(c):
    """What the planner does with the requests of each kind, and why."""

    def decide(x):
        w, index = next((w, index) for name, w, index in REQUESTS if name == x["request"])
        d = planner.choose_path(w, index)
        return [(x["request"], d.path, d.reason, x["n_requests"])]

    return planned(asked(c, KIND), decide, "request string, path string, reason string, n_requests long")


ASKED = {
    "top-k by the index's metric": planner.Workload(1_000, 8, k=10, metric="ip"),
    "top-k by another metric": planner.Workload(1_000, 8, k=10, metric="l1"),
    "range": planner.Workload(1_000, 8, k=None, metric="ip"),
    "exact": planner.Workload(1_000, 8, k=10, metric="ip", min_recall=1.0),
}


FORM = {"asked": turn("event_id", text(ASKED))}
SQL_ANSWERS = ", ".join(f"({t}, 'scan', TRUE), ({t}, 'index', {str(w.endswith(chr(39) + 's metric')).upper()})" for w, t in zip(ASKED, text(ASKED)))


@query("access_path_matrix", f"SELECT t.*, n_requests FROM (VALUES {SQL_ANSWERS}) t(asked, path, answers) JOIN ({sql_asked(FORM)}) USING (asked)")
def _(c):
    """What each kind of path can answer of the requests, by the planner's rules: a scan everything, an index only top-k by its own metric."""

    def decide(x):
        allowed, _ = planner.capabilities(planner.IndexInfo("ip"), ASKED[x["asked"]])
        return [(x["asked"], "scan", "scan" in allowed, x["n_requests"]), (x["asked"], "index", "graph" in allowed, x["n_requests"])]

    return planned(asked(c, FORM), decide, "asked string, path string, answers boolean, n_requests long")


@query("adaptive_topk", sql_topk(sql_queries(10), MIX, 10, CHEAP))
def _(c):
    return search(c.mix_orders(), block(c, 10), 10, cond=F.expr(CHEAP)).select("query_id", "rank", "vec_id", u6())


def _sql_regret() -> str:
    cells = "(SELECT CAST(s AS DOUBLE) AS s, b, d, path, CAST(ms AS DOUBLE) AS ms, n_requests FROM (" + SQL_MEASURED + "))"
    best = f"(SELECT s, b, d, min(ms) AS least FROM {cells} GROUP BY s, b, d)"
    modelled = " UNION ALL ".join(f"SELECT s, b, d, '{p}' AS path, {sql_cost(p, '1000000.0', '(s / 100)', 'b', 'd', double)} AS cost FROM {best}" for p in planner.PATHS)
    chosen = f"SELECT s, b, d, min_by(path, cost) AS path FROM ({modelled}) GROUP BY s, b, d"
    fixed = f"SELECT path AS policy, ms / least AS r, n_requests AS n FROM {cells} JOIN {best} USING (s, b, d)"
    model = f"SELECT 'cost model' AS policy, ms / least AS r, n_requests AS n FROM ({chosen}) JOIN {cells} USING (s, b, d, path) JOIN {best} USING (s, b, d)"
    return f"""SELECT policy, CAST(round(1000 * max(r)) AS BIGINT) AS worst_milli, CAST(round(1000 * sum(r * n) / sum(n)) AS BIGINT) AS mean_milli
FROM ({fixed} UNION ALL {model}) GROUP BY policy"""


@query("policy_regret", _sql_regret())
def _(c):
    """Time of each policy over the best path's, worst and mean over the requests, in thousandths."""

    def decide(x):
        cell = (x["s"], x["b"], x["d"])
        times = {p: published.FILTER_MS[x["b"], x["d"]][p][published.SCAN_PERCENT.index(x["s"])] for p in planner.PATHS}
        chosen = {p: p for p in planner.PATHS} | {"cost model": planner.choose_path(_load(x), INDEXED).path}
        return [(policy, planner.regret({cell: times}, {cell: path})[cell], x["n_requests"]) for policy, path in chosen.items()]

    each = planned(asked(c, CELL), decide, "policy string, r double, n long")
    milli = lambda x, name: F.round(1000 * x).cast("long").alias(name)
    return each.groupBy("policy").agg(milli(F.max("r"), "worst_milli"), milli(F.sum(F.col("r") * F.col("n")) / F.sum("n"), "mean_milli"))


@query(
    "approx_selectivity",
    " UNION ALL ".join(
        f"SELECT {bound} AS bound, CAST(round(1000000.0 * count(*) FILTER (o_totalprice < {bound}) / count(*)) AS BIGINT) AS exact_u6, TRUE AS within_tol FROM orders"
        for bound in LADDER.values()
    ),
)
def _(c):
    """Fractions below the bounds of the ladder from a quantile sketch of the column, within 5 points of the exact ones."""
    p = F.col("o_totalprice")
    found = c.orders.agg(
        F.expr("kll_sketch_agg_double(o_totalprice)").alias("sketch"), F.count(F.lit(1)).alias("n"),
        *(F.count_if(p < x).alias(f"below_{x}") for x in LADDER.values()),
    )
    rows = F.explode(F.array(*(
        F.struct(
            F.lit(x).alias("bound"), (F.col(f"below_{x}") / F.col("n")).alias("exact"),
            F.expr(f"kll_sketch_get_rank_double(sketch, {float(x)}D)").alias("rank"),
        ) for x in LADDER.values()
    )))
    each = found.select(rows.alias("x")).select("x.*")
    return each.select("bound", F.round(F.col("exact") * 1_000_000).cast("long").alias("exact_u6"), (F.abs(F.col("rank") - F.col("exact")) < 0.05).alias("within_tol"))


@query("adaptive_three_paths", f"""SELECT 'matrix' AS forced, 10 AS k, t.* FROM ({sql_topk(sql_queries(10), MIX, 10, CHEAP)}) t
UNION ALL SELECT 'scan', 10, t.* FROM ({sql_topk(sql_queries(10), MIX, 10, CHEAP)}) t
UNION ALL SELECT 'graph', 10, t.* FROM ({sql_topk(sql_queries(10), MIX, 10, CHEAP)}) t""")
def _(c):
    """The same answer by each path, with an index at hand: hints force each, the graph saturated."""
    from .graphs import FULL, index

    out = None
    for path in planner.PATHS:
        one = search(c.mix_orders(), block(c, 10), 10, cond=F.expr(CHEAP), index=index(c), ef=FULL, hint=path)
        one = one.select(F.lit(path).alias("forced"), F.lit(10).alias("k"), "query_id", "rank", "vec_id", u6())
        out = one if out is None else out.unionByName(one)
    return out
