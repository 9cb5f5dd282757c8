"""Registered queries of measures, models, generators and experiment workloads, with their SQL."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..plans import templates as T
from ..plans.templates import TreeTemplate
from ..sources import graphs as G
from . import counting as C
from . import exact as X
from . import exchange as E
from . import model as M
from . import workloads as W
from .queries import PAIRS, QUERIES, SEED, SQL, _binomial_sql, color_sql, colorful_sql, graph_sql, joins_sql, register, subset_sql

_U5 = TreeTemplate.named("u5-2")
_PS = f"WITH {graph_sql('part_supplier')}"
_PL = f"WITH {graph_sql('page_link')}"
_deg = "d AS (SELECT src AS v, count(*) AS deg FROM e GROUP BY 1)"


def block_sql(v: str, p: int) -> str:
    return f"({v} % 2147483647 * 48271 + 11) % 2147483647 % {p}"


# -- generator ----------------------------------------------------------------------------------

def rmat_sql(scale: int, edges: int, skew: int, seed: int = 42) -> str:
    """The generator's pairs, from the definition of its hashes."""
    p, (a, b, c, _) = 2147483647, G.SKEW[skew]

    def quadrant(level: int) -> str:
        salt = seed * 1000 + level
        square = lambda x, add: f"list_transform([{x}], lambda z: (z * z + {add}) % {p})[1]"
        return f"({square(f'({square(f'(i % {p} * 48271 + {salt * 7919 % p}) % {p}', salt % p)} * 16807 + 12345) % {p}', 0)} % 100)"

    qs = ", ".join(f"{quadrant(n)} AS q{n}" for n in range(scale))
    src = " + ".join(f"(q{n} >= {a + b})::BIGINT * {1 << scale - 1 - n}" for n in range(scale))
    dst = " + ".join(f"((q{n} >= {a} AND q{n} < {a + b}) OR q{n} >= {a + b + c})::BIGINT * {1 << scale - 1 - n}" for n in range(scale))
    return f"SELECT {src} AS a, {dst} AS b FROM (SELECT {qs} FROM (SELECT unnest(range({edges})) AS i))"


for _runs in W.WORKLOADS.values():
    for _r in _runs:
        if _r.graph.startswith("rmat"):
            PAIRS[_r.graph] = rmat_sql(*map(int, _r.graph.split("_")[1:]))
PAIRS["rmat_10_20000_3"] = rmat_sql(10, 20_000, 3)
SQL["rmat_edges_s10"] = f"WITH {graph_sql('rmat_10_20000_3')} SELECT src, dst FROM e"


def _stats(g):
    return X.degrees(g).agg(F.expr("cast(sum(deg) div 2 as bigint)").alias("e"), F.count("*").alias("v"), F.max("deg").alias("max_deg"))


def _stats_sql(name):
    return f"SELECT '{name}' AS graph, (sum(deg) // 2)::BIGINT AS e, count(*) AS v, max(deg) AS max_deg FROM (WITH {graph_sql(name)} SELECT src, count(*) AS deg FROM e GROUP BY 1)"


_WEAK = ("rmat_8_1000_3", "rmat_9_2000_3")


@register("weak_scaling_stats", " UNION ALL ".join(_stats_sql(g) for g in _WEAK))
def weak_scaling_stats(spark, d):
    """Achieved sizes and largest degrees where vertices and edges grow with the blocks."""
    parts = [_stats(G.EdgeGraph(G.edges_of(G.rmat(spark, *map(int, g.split("_")[1:]))))).select(F.lit(g).alias("graph"), "e", "v", "max_deg") for g in _WEAK]
    return parts[0].unionByName(parts[1])


# graphs numbered by hashes: the same sizes from the strings themselves
_line = "SELECT DISTINCT doc_id::VARCHAR AS a, 'l' || trim(l) AS b FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS l FROM documents) WHERE length(trim(l)) >= 20"
_conv = "SELECT DISTINCT conv_id::VARCHAR AS a, 'l' || role || chr(0) || text AS b FROM conversations"
for _g, _pairs in (("doc_line", _line), ("conv_text", _conv)):
    SQL[f"graph_stats_{_g}"] = f"WITH p AS ({_pairs}), d AS (SELECT a AS v, count(*) AS deg FROM p GROUP BY 1 UNION ALL SELECT b, count(*) FROM p GROUP BY 1) SELECT (sum(deg) // 2)::BIGINT AS e, count(*) AS v, round(avg(deg), 6) AS avg_deg, max(deg) AS max_deg FROM d"


# -- cost model ---------------------------------------------------------------------------------

# the plan of the five-vertex path cuts all but its root at each step
_steps = f"s AS (SELECT (t - 1)::INT AS sub, t::INT AS size, {_binomial_sql('5', 't')}::BIGINT AS sets, t::BIGINT AS splits FROM (SELECT unnest([2, 3, 4, 5]) AS t))"
_sizes = f"{graph_sql('part_supplier')}, g AS (SELECT (SELECT count(*) FROM vs)::DOUBLE AS v, (SELECT count(*) FROM e)::DOUBLE AS n)"
_model = f"{_sizes}, {_steps}, m AS (SELECT sub, size, step::INT AS step, sets * splits * (n / 25 * 1e-9) AS comp, 1e-4 + sets * (8 * n / 25 * 1e-9) AS comm, sets * (8.0 * (v / 5 + n / 25)) AS mem FROM s, g, (SELECT unnest(range(1, 5)) AS step)), r AS (SELECT *, lag(comp) OVER (PARTITION BY sub ORDER BY step) AS before FROM m)"
_micro = lambda *names: [F.round(F.col(n) * 1e6, 3).alias(n) for n in names]


def _pairs_of(spark, d):
    return G.graph(spark, d, "part_supplier").edges.agg(F.count_distinct("src").alias("v"), F.count("*").alias("n")).first()


def _model_steps(spark, d):
    n = _pairs_of(spark, d)
    return M.model_steps(spark, _U5, n["v"], n["n"], 5)


register("model_steps", f"WITH {_model} SELECT sub, size, step, round(comp * 1e6, 3) AS comp, round(comm * 1e6, 3) AS comm, round(mem, 3) AS mem FROM m")(
    lambda spark, d: _model_steps(spark, d).select("sub", "size", "step", *_micro("comp", "comm"), F.round("mem", 3).alias("mem")))
register("model_rho", f"WITH {_model} SELECT sub, step, round(CASE WHEN before IS NOT NULL THEN least(before, comm) / comm END, 6) AS rho FROM r")(
    lambda spark, d: M.with_overlap(_model_steps(spark, d)).select("sub", "step", F.round("rho", 6).alias("rho")))
register("model_totals", f"WITH {_model} SELECT sub, round(sum(comp) * 1e6, 3) AS comp, round(sum(comm * (1 - CASE WHEN before IS NULL THEN 0 ELSE least(before, comm) / comm END)) * 1e6, 3) AS comm, round(max(mem), 3) AS mem FROM r GROUP BY 1")(
    lambda spark, d: M.totals(_model_steps(spark, d)).select("sub", *_micro("comp", "comm"), F.round("mem", 3).alias("mem")))
_cut12 = T.split_plan(TreeTemplate.named("u12-2")).steps[-1].sizes[2]
register("model_large_comm", f"WITH {_sizes} SELECT p::INT AS p, round((1e-4 + 8e-9 * {_binomial_sql('12', str(_cut12))} * n / (p * p)) * 1e6, 3) AS comm, round((1e-4 + 8e-9 * {_binomial_sql('12', str(_cut12))} * n / (p * p * p)) * 1e6, 3) AS comm_printed FROM g, (SELECT unnest([4, 8, 16, 25]) AS p)")(
    lambda spark, d: M.large_template_comm(spark, TreeTemplate.named("u12-2"), _pairs_of(spark, d)["n"], [4, 8, 16, 25]).select("p", *_micro("comm", "comm_printed")))

_remote = f"n AS (SELECT {block_sql('src', 5)} AS blk, ({block_sql('src', 5)} - {block_sql('dst', 5)} + 5) % 5 AS step, count(*) AS n FROM e GROUP BY 1, 2), {_steps}, x AS (SELECT sub, blk::INT AS blk, step::INT AS step, n, sets, splits FROM n, s WHERE step > 0)"


def _remote_of(spark, d):
    g = G.EdgeGraph(E.written(G.graph(spark, d, "part_supplier").edges, "edges"))
    own = g.nodes().groupBy(E.block_of(F.col("v"), 5).alias("blk")).agg(F.count("*").alias("v"))
    return E.remote_neighbors(g.edges, 5), own


register("model_comp", f"{_PS}, {_remote} SELECT sub, blk, step, (n * sets * splits)::BIGINT AS comp FROM x")(lambda spark, d: M.measured_comp(_remote_of(spark, d)[0], _U5))
register("model_peak_mem", f"{_PS}, {_remote}, o AS (SELECT ({block_sql('v', 5)})::INT AS blk, count(*) AS v FROM vs GROUP BY 1) SELECT sub, blk, max(sets * (v + n))::BIGINT AS mem FROM x JOIN o USING (blk) GROUP BY 1, 2")(
    lambda spark, d: M.measured_memory(*_remote_of(spark, d), _U5))
_timed = f"{_remote}, t AS (SELECT sub, blk, step, n * sets * splits * 1e-9 AS comp, 1e-4 + n * sets * 8e-9 AS comm FROM x), u AS (SELECT *, greatest(comm, coalesce(lag(comp) OVER k, 0)) AS time, lag(comp) OVER k AS before FROM t WINDOW k AS (PARTITION BY sub, blk ORDER BY step)), l AS (SELECT *, max(time) OVER (PARTITION BY sub, step) - time AS late FROM u), w AS (SELECT *, coalesce(lag(late) OVER (PARTITION BY sub, blk ORDER BY step), 0) AS wait FROM l)"
register("model_wait", f"{_PS}, {_timed} SELECT sub, blk, step, round(time * 1e6, 3) AS time, round(wait * 1e6, 3) AS wait FROM w")(
    lambda spark, d: M.with_waits(M.measured_comm(_remote_of(spark, d)[0], _U5)).select("sub", "blk", "step", *_micro("time", "wait")))
register("model_comm", f"{_PS}, {_timed} SELECT sub, blk, round(sum(comp) * 1e6, 3) AS comp, round(sum((comm + wait) * (1 - CASE WHEN before IS NULL THEN 0 ELSE least(before, comm + wait) / (comm + wait) END)) * 1e6, 3) AS comm FROM w GROUP BY 1, 2")(
    lambda spark, d: M.totals_with_waits(M.measured_comm(_remote_of(spark, d)[0], _U5)).select("sub", "blk", *_micro("comp", "comm")))
# a line's pieces as what is sent, its price as what that takes
register("model_fit", "SELECT round(regr_intercept(l_extendedprice, l_quantity), 3) AS alpha, round(regr_slope(l_extendedprice, l_quantity), 6) AS beta FROM lineitem")(
    lambda spark, d: M.fitted_rates(spark.read.parquet(f"{d}/lineitem.parquet").select(F.col("l_quantity").alias("bytes"), F.col("l_extendedprice").alias("sec"))).select(F.round("alpha", 3).alias("alpha"), F.round("beta", 6).alias("beta")))
SQL["n_colorings_grid"] = """WITH g AS (SELECT k::INT AS k, eps, delta FROM (SELECT unnest([3, 5, 7]) AS k), (SELECT DISTINCT l_discount AS eps, l_tax AS delta FROM lineitem WHERE l_discount > 0 AND l_tax > 0 AND l_tax < 1)),
t AS (SELECT *, ceil(ln(1 / delta))::INT + 1 - ceil(ln(1 / delta))::INT % 2 AS t FROM g) SELECT k, eps, delta, (ceil(ceil(exp(k) * ln(1 / delta) / (eps * eps)) / t) * t)::INT AS n, t::INT AS t FROM t"""
SQL["exchange_volume_u5_2"] = f"{_PS}, {_steps}, q AS (SELECT count(*) AS n FROM (SELECT DISTINCT dst, {block_sql('src', 5)} FROM e WHERE {block_sql('src', 5)} <> {block_sql('dst', 5)})) SELECT sub AS step, (size - 1)::INT AS cut_size, (n * w)::BIGINT AS entries, (n * w * 8)::BIGINT AS bytes FROM q, (SELECT sub, size, {_binomial_sql('5', '(size - 1)')} AS w FROM s)"
SQL["task_size_sweep"] = f"WITH {graph_sql('hub')}, r AS (SELECT src, row_number() OVER (PARTITION BY src ORDER BY dst) - 1 AS i FROM e), t AS (SELECT s, src, i // s AS slot, count(*) AS n FROM r, (SELECT unnest([10, 20, 40, 50, 60, 100, 200, 1000]) AS s) GROUP BY 1, 2, 3) SELECT count(*) AS tasks, max(n) AS max_n, round(avg(n), 6) AS avg_n, round(stddev_pop(n), 6) AS sd_n, s::INT AS s FROM t GROUP BY s"


# -- measures of runs, over a made-up log --------------------------------------------------------

_LOG_SQL = "g AS (SELECT (i % 6)::INT AS stage, i AS task, i % 6 * 1000 + i * 37 % 400 AS start_ms, i % 6 * 1000 + i * 37 % 400 + 50 + i * 53 % 300 AS finish_ms, i * 7 % 20 AS fetch_wait_ms, (i * 3 % 10)::DOUBLE AS write_ms, i * 1009 % 5000 AS shuffle_write, i * 7919 % 100000 AS peak_mem FROM (SELECT unnest(range(300)) AS i))"


def _log(spark):
    i = F.col("id")
    start = i % 6 * 1000 + i * 37 % 400
    return spark.range(300).select(
        (i % 6).cast("int").alias("stage"), i.alias("task"), start.alias("start_ms"), (start + 50 + i * 53 % 300).alias("finish_ms"), (i * 7 % 20).alias("fetch_wait_ms"),
        (i * 3 % 10).cast("double").alias("write_ms"), (i * 1009 % 5000).alias("shuffle_write"), (i * 7919 % 100000).alias("peak_mem"))


_SWEEP = f"{_LOG_SQL}, p AS (SELECT start_ms AS t, 1 AS d FROM g UNION ALL SELECT finish_ms, -1 FROM g), q AS (SELECT t, sum(d) AS d FROM p GROUP BY 1), h AS (SELECT sum(d) OVER (ORDER BY t) AS running, lead(t) OVER (ORDER BY t) - t AS ms FROM q)"
register("time_shares", f"WITH {_LOG_SQL} SELECT round(sum(fetch_wait_ms + write_ms), 6) AS comm_ms, round(sum(finish_ms - start_ms) - sum(fetch_wait_ms + write_ms), 6) AS comp_ms, round(sum(fetch_wait_ms + write_ms) / sum(finish_ms - start_ms), 6) AS comm_share FROM g")(
    lambda spark, d: M.time_shares(_log(spark)).select(*[F.round(c, 6).alias(c) for c in ("comm_ms", "comp_ms", "comm_share")]))
register("peak_memory", f"WITH {_LOG_SQL} SELECT stage, max(peak_mem) AS peak_mem, sum(shuffle_write)::BIGINT AS moved FROM g GROUP BY 1")(lambda spark, d: M.peak_memory(_log(spark)))
# an order as a task: from its date to the last shipment of its lines
_DAY = 86_400_000
_OPEN_SQL = f"g AS (SELECT date_diff('day', DATE '1970-01-01', o_orderdate::DATE) * {_DAY} AS start_ms, date_diff('day', DATE '1970-01-01', last::DATE) * {_DAY} AS finish_ms FROM orders JOIN (SELECT l_orderkey, max(l_shipdate) AS last FROM lineitem GROUP BY 1) ON l_orderkey = o_orderkey WHERE last::DATE > o_orderdate::DATE)"
_OPEN_SWEEP = _SWEEP.replace(_LOG_SQL, _OPEN_SQL)


def _open_orders(spark, d):
    o, li = (spark.read.parquet(f"{d}/{t}.parquet") for t in ("orders", "lineitem"))
    last = li.groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(F.max("l_shipdate").alias("last"))
    ms = lambda c: (F.unix_date(F.to_date(c)).cast("long") * _DAY)
    return o.join(last, "o_orderkey").select(ms("o_orderdate").alias("start_ms"), ms("last").alias("finish_ms")).where("finish_ms > start_ms")


register("concurrency_histogram", f"WITH {_OPEN_SWEEP} SELECT running::BIGINT AS running, sum(ms)::BIGINT AS ms FROM h WHERE ms IS NOT NULL GROUP BY 1")(lambda spark, d: M.concurrency_histogram(_open_orders(spark, d)).select("running", F.col("ms").cast("long").alias("ms")))
register("average_concurrency", f"WITH {_OPEN_SWEEP} SELECT round(sum(running * ms) / sum(ms), 6) AS average FROM h WHERE ms IS NOT NULL AND running > 0")(lambda spark, d: M.average_concurrency(_open_orders(spark, d)).select(F.round("average", 6).alias("average")))
_SPANS_SQL = "x AS (SELECT o_orderkey AS step, date_diff('day', DATE '1970-01-01', o_orderdate::DATE)::DOUBLE AS t, date_diff('day', DATE '1970-01-01', l_shipdate::DATE)::DOUBLE AS c FROM orders JOIN lineitem ON l_orderkey = o_orderkey), s AS (SELECT step, min(t) AS t0, max(c) AS t1, min(c) AS c0, max(c) AS c1 FROM x GROUP BY 1)"


@register("measured_rho_spans", f"WITH {_SPANS_SQL} SELECT a.step, CASE WHEN a.t1 > a.t0 THEN greatest(least(a.t1, b.c1) - greatest(a.t0, b.c0), 0) / (a.t1 - a.t0) ELSE 0 END AS rho FROM s a JOIN s b ON a.step = b.step + 1")
def rho_spans(spark, d):
    """Orders as steps: an order is transferred from its date to its last shipment and computed between its shipments."""
    o, li = (spark.read.parquet(f"{d}/{t}.parquet") for t in ("orders", "lineitem"))
    day = lambda c: F.unix_date(F.to_date(c)).cast("double")
    x = o.join(li, F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_orderkey").alias("step"), day("o_orderdate").alias("t"), day("l_shipdate").alias("c"))
    spans = x.groupBy("step").agg(F.min("t").alias("t0"), F.max("c").alias("t1"), F.min("c").alias("c0"), F.max("c").alias("c1"))
    each = F.array(*[F.struct("step", F.lit(kind).alias("kind"), F.col(f"{kind[0]}0").alias("start"), F.col(f"{kind[0]}1").alias("finish")) for kind in ("transfer", "compute")])
    return M.measured_rho(spans.select(F.explode(each).alias("x")).select("x.*"))


# -- accuracy -----------------------------------------------------------------------------------

_SEEDS = list(range(1, 37))


def _error_sql(graph: str, its: list[int]) -> str:
    est = f"SELECT it, colorful * {T.scale_up(3)!r}::DOUBLE AS estimate FROM ({colorful_sql(graph, TreeTemplate.named('u3-1'), its)})"
    return f"SELECT it, estimate, exact FROM ({est}), (WITH {graph_sql(graph)}, d AS (SELECT count(*) AS n FROM e GROUP BY src) SELECT sum(n * (n - 1) // 2)::BIGINT AS exact FROM d)"


def _errors(spark, d, graph, its):
    g = G.EdgeGraph(E.written(G.graph(spark, d, graph).edges, "edges"))
    x = C.unbias(C.colorful_count(g, TreeTemplate.named("u3-1"), its, SEED), 3)
    return x.join(X.exact_path3(g), F.lit(True))


for _g in ("knn", "cust_part", "part_supplier"):
    register(f"relative_error_{_g}", f"SELECT it, exact, round(abs(estimate - exact) / exact, 6) AS error FROM ({_error_sql(_g, [1, 2, 3])})")(
        lambda spark, d, g=_g: _errors(spark, d, g, [1, 2, 3]).select("it", "exact", F.round(F.abs(F.col("estimate") - F.col("exact")) / F.col("exact"), 6).alias("error")))


@register("eps_delta_hit_rate", f"SELECT count(*) AS seeds, round(avg((abs(z - exact) <= 0.2 * exact)::INT), 6) AS hit_rate FROM (SELECT it % 12 AS g, avg(estimate) AS z, max(exact) AS exact FROM ({_error_sql('knn', _SEEDS)}) GROUP BY 1)")
def hit_rate(spark, d):
    """Share of twelve independent means of three colourings that lie within a fifth of the exact count."""
    z = _errors(spark, d, "knn", _SEEDS).groupBy(F.pmod("it", F.lit(12)).alias("g")).agg(F.avg("estimate").alias("z"), F.max("exact").alias("exact"))
    return z.agg(F.count("*").alias("seeds"), F.round(F.avg((F.abs(F.col("z") - F.col("exact")) <= 0.2 * F.col("exact")).cast("int")), 6).alias("hit_rate"))


_cherry = "FROM e e1 JOIN e e2 ON e2.src = e1.src AND e1.dst < e2.dst JOIN col a ON a.v = e1.src JOIN col b ON b.v = e1.dst JOIN col c ON c.v = e2.dst"


@register("colorful_rate_u3_1", f"{_PL}, {color_sql(3, [1])} SELECT count(*) AS occurrences, round(avg((a.c <> b.c AND a.c <> c.c AND b.c <> c.c)::INT), 6) AS rate {_cherry}")
def colorful_rate(spark, d):
    """Share of the occurrences of three vertices in a star whose colours all differ; 2/9 is expected."""
    g = G.EdgeGraph(E.written(G.graph(spark, d, "page_link").edges, "edges"))
    col = C.assign_colors(g.nodes(), 3, [1], SEED).select("v", "mask")
    e = g.edges.join(col.withColumnRenamed("v", "src").withColumnRenamed("mask", "m"), "src").join(col.withColumnRenamed("v", "dst").withColumnRenamed("mask", "n"), "dst")
    two = e.select("src", "m", F.col("dst").alias("b"), "n").join(e.select("src", F.col("dst").alias("c"), F.col("n").alias("o")), "src").where("b < c")
    return two.agg(F.count("*").alias("occurrences"), F.round(F.avg((F.expr("m | n | o") == 7).cast("int")), 6).alias("rate"))


# -- exact and existence ------------------------------------------------------------------------

_tri = "SELECT count(*) AS t FROM p x JOIN p y ON x.b = y.a JOIN p z ON z.a = x.a AND z.b = y.b"
register("exact_path4_co_order", f"WITH {graph_sql('co_order')}, {_deg} SELECT (sum((x.deg - 1) * (y.deg - 1)) - 3 * (SELECT t FROM ({_tri})))::BIGINT AS exact FROM p JOIN d x ON x.v = a JOIN d y ON y.v = b")(
    lambda spark, d: X.exact_path4(G.graph(spark, d, "co_order")))
_five = "e a JOIN e b ON b.src = a.dst AND b.dst <> a.src JOIN e c ON c.src = b.dst AND c.dst NOT IN (a.src, a.dst) JOIN e f ON f.src = c.dst AND f.dst NOT IN (a.src, a.dst, b.dst)"
register("exact_u5_2_knn", f"WITH {graph_sql('knn')} SELECT (count(*) // 2)::BIGINT AS exact FROM {_five}")(lambda spark, d: X.exact_path5(G.graph(spark, d, "knn")))
register("four_cycles_page_link", f"{_PL} SELECT (sum(n * (n - 1) // 2) // 2)::BIGINT AS cycles FROM (SELECT x.dst AS a, y.dst AS b, count(*) AS n FROM e x JOIN e y ON y.src = x.src AND x.dst < y.dst GROUP BY 1, 2)")(
    lambda spark, d: X.four_cycles(G.graph(spark, d, "page_link")))
register("four_cycles_knn", f"WITH {graph_sql('knn')} SELECT (sum(n * (n - 1) // 2) // 2)::BIGINT AS cycles FROM (SELECT x.dst AS a, y.dst AS b, count(*) AS n FROM e x JOIN e y ON y.src = x.src AND x.dst < y.dst GROUP BY 1, 2)")(
    lambda spark, d: X.four_cycles(G.graph(spark, d, "knn")))


def _exists(graph, template, fail):
    return lambda spark, d: spark.createDataFrame([(template, C.tree_exists(G.graph(spark, d, graph), TreeTemplate.named(template), fail))], "template string, found boolean")


register("tree_exists_path4_page_link", f"{_PL} SELECT 'path4' AS template, count(*) > 0 AS found FROM e x JOIN e y ON y.src = x.dst AND y.dst <> x.src JOIN e z ON z.src = y.dst AND z.dst NOT IN (x.src, x.dst)")(_exists("page_link", "path4", 0.01))
# conversations and their turns form separate stars, so no path of four vertices
register("tree_exists_path4_conv_text", f"WITH p AS ({_conv}), d AS (SELECT b, count(*) AS n FROM p GROUP BY 1) SELECT 'path4' AS template, count(*) > 0 AS found FROM p x JOIN d ON d.b = x.b AND d.n > 1 JOIN p y ON y.a = x.a AND y.b <> x.b")(_exists("conv_text", "path4", 0.1))
register("tree_exists_u5_2_knn", f"WITH {graph_sql('knn')} SELECT 'u5-2' AS template, count(*) > 0 AS found FROM {_five}")(_exists("knn", "u5-2", 0.01))


# -- workloads ----------------------------------------------------------------------------------

def _run_sql(workload: str) -> str:
    rows = []
    for r in W.WORKLOADS[workload]:
        t = TreeTemplate.named(r.template)
        count = (colorful_sql if t.k <= 3 else subset_sql)(r.graph, t, [1])
        asked = f"WITH {graph_sql(r.graph)} SELECT count(*) FROM (SELECT DISTINCT dst, {block_sql('src', r.p)} FROM e WHERE {block_sql('src', r.p)} <> {block_sql('dst', r.p)})"
        rows.append(f"SELECT '{r.graph}' AS graph, '{r.template}' AS template, '{r.mode}' AS mode, {r.p}::INT AS p, {r.s}::INT AS s, (SELECT colorful::VARCHAR FROM ({count})) AS colorful, ({asked}) AS requests")
    return " UNION ALL ".join(rows)


def _workload(name):
    # seconds and speed-ups differ from run to run: W.run has them, the checked columns leave them out
    return lambda spark, d: W.run(spark, d, name).select("graph", "template", "mode", "p", "s", "colorful", "requests")


for _w in W.WORKLOADS:
    register(_w, _run_sql(_w))(_workload(_w))

register("w3_overlap_measured", "SELECT (i + 1)::INT AS step, true AS sound FROM (SELECT unnest(range(4)) AS i)")(
    lambda spark, d: W.overlap(spark, d, "page_link", "u5-2", 5).select("step", F.col("rho").between(0.0, 1.0).alias("sound")))
_peak = "SELECT p::INT AS p, round((SELECT max(sets) FROM s) * 8.0 * (1000.0 / p + 100000.0 / (p * p)), 3) AS staged, round((SELECT max(sets) FROM s) * 8.0 * (1000.0 / p + 100000.0 / p), 3) AS bulk FROM (SELECT unnest([4, 6, 8, 10]) AS p)"


@register("w10_peak_memory", f"WITH {_steps} {_peak}")
def peak_by_blocks(spark, d):
    """Modelled peak bytes a block of a staged exchange and of one that holds all neighbours' counts at once."""
    out = None
    for p in (4, 6, 8, 10):
        x = M.model_steps(spark, _U5, 1000, 100_000, p).agg(F.max("mem").alias("staged"))
        top = max(math.comb(5, s.sizes[0]) for s in T.split_plan(_U5).steps)
        x = x.select(F.lit(p).alias("p"), F.round("staged", 3).alias("staged"), F.round(F.lit(8.0 * top * (1000 / p + 100_000 / p)), 3).alias("bulk"))
        out = x if out is None else out.unionByName(x)
    return out


@register("w12_communication_share", "SELECT template, p::INT AS p, true AS sound FROM (SELECT unnest(['u3-1', 'u5-2', 'u7-2']) AS template, 4 AS p)")
def communication_share(spark, d):
    return W.shares(spark, W.run(spark, d, "w11_overall")).select("template", "p", F.col("comm_share").between(0.0, 1.0).alias("sound"))
