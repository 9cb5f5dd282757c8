"""Registered queries of the surrounding operators: sources and sinks, joins, aggregates, windows, sets, functions, streams."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import packed, tables
from ..plans import templates as T
from ..plans.templates import TreeTemplate
from ..sources import events as V
from ..sources import graphs as G
from ..streaming import windows as S
from . import counting as C
from . import exact as X
from . import exchange as E
from . import neighborhood as N
from .queries import SEED, color_sql, colorful_sql, graph_sql, register

_PS = f"WITH {graph_sql('part_supplier')}"
_HUB = f"WITH {graph_sql('hub')}"
_PL = f"WITH {graph_sql('page_link')}"
_deg = "d AS (SELECT src AS v, count(*) AS deg FROM e GROUP BY 1)"


# -- sources and sinks --------------------------------------------------------------------------

def _roundtrip(fmt):
    def run(spark, d):
        path = E.fresh_path(spark, f"edges-{fmt}")
        return G.read_edge_list(spark, G.write_edge_list(G.graph(spark, d, "part_supplier").edges, path, fmt), fmt)

    return run


for _fmt in ("csv", "json"):
    register(f"scan_edges_{_fmt}_roundtrip", f"{_PS} SELECT src, dst FROM e")(_roundtrip(_fmt))


@register("scan_edges_text_roundtrip", f"{_PS} SELECT src, dst FROM e")
def text_roundtrip(spark, d):
    path = E.fresh_path(spark, "edges-text")
    G.graph(spark, d, "part_supplier").edges.select(F.concat_ws(" ", "src", "dst").alias("value")).write.text(path)
    return G.read_edge_list(spark, path, "text")


@register("sink_bucketed_edges", f"{_PS} SELECT src, dst FROM e")
def bucketed(spark, d):
    name = "edges_" + E.fresh_path(spark, "b").rsplit("-", 1)[1]
    return G.save_bucketed(G.graph(spark, d, "part_supplier").edges, name, 8).select("src", "dst")


_lists = "SELECT src AS v, string_agg(dst::VARCHAR, ',' ORDER BY dst) AS nbrs, count(*) AS n FROM e GROUP BY 1"
register("adjacency_lists", f"WITH {graph_sql('cust_part')} {_lists}")(
    lambda spark, d: N.adjacency(G.graph(spark, d, "cust_part")).select("v", F.concat_ws(",", F.col("nbrs").cast("array<string>")).alias("nbrs"), F.size("nbrs").cast("long").alias("n")))
register("adjacency_explode", f"WITH {graph_sql('cust_part')} SELECT src AS v, (row_number() OVER (PARTITION BY src ORDER BY dst) - 1)::INT AS pos, dst AS u FROM e")(
    lambda spark, d: N.from_adjacency(N.adjacency(G.graph(spark, d, "cust_part"))))
register("orient_by_degree", f"WITH {graph_sql('co_order')}, {_deg} SELECT src, dst FROM e JOIN d x ON x.v = src JOIN d y ON y.v = dst WHERE (x.deg, src) < (y.deg, dst)")(
    lambda spark, d: N.orient(G.graph(spark, d, "co_order")))


# -- joins --------------------------------------------------------------------------------------

def _colored(spark, d, graph="part_supplier", k=3):
    g = G.graph(spark, d, graph)
    return g, C.assign_colors(g.nodes(), k, [1], SEED)


register("join_inner_edges_colors", f"{_PS}, {color_sql(3, [1])} SELECT src, dst, (1 << x.c::INT)::INT AS src_mask, (1 << y.c::INT)::INT AS dst_mask FROM e JOIN col x ON x.v = src JOIN col y ON y.v = dst")(
    lambda spark, d: N.color_edges(*_colored(spark, d)))
register("join_left_isolated", f"{_PS}, {_deg} SELECT p_partkey * 16 + 2 AS v, coalesce(deg, 0)::BIGINT AS deg FROM part LEFT JOIN d ON v = p_partkey * 16 + 2")(
    lambda spark, d: N.degrees_of(G.graph(spark, d, "part_supplier"), spark.read.parquet(f"{d}/part.parquet").select(G.vid(F.col("p_partkey"), "part"))))
_blk = lambda v, p=5: f"(({v} % 2147483647 * 48271 + 11) % 2147483647 % {p})"


@register("join_semi_requested", f"{_PS}, {color_sql(3, [1])} SELECT DISTINCT it::INT AS it, v, (1 << c::INT)::INT AS mask, 1::BIGINT AS cnt FROM col JOIN e ON e.dst = v WHERE {_blk('src')} = 0 AND {_blk('dst')} <> 0")
def semi_requested(spark, d):
    g, col = _colored(spark, d)
    wanted = E.build_requests(g.edges, 5).where("to_blk = 0").select(F.col("u").alias("v"))
    return C.init_counts(col).join(wanted, "v", "left_semi").select("it", "v", "mask", "cnt")


register("messages_p5", f"{_PS}, {color_sql(3, [1])} SELECT DISTINCT {_blk('src')}::INT AS to_blk, it::INT AS it, v, (1 << c::INT)::INT AS mask, 1::BIGINT AS cnt FROM col JOIN e ON e.dst = v WHERE {_blk('src')} <> {_blk('dst')}")(
    lambda spark, d: (lambda g, col: E.messages(C.init_counts(col), E.build_requests(g.edges, 5)))(*_colored(spark, d)))
register("join_anti_unreached", "SELECT p_partkey * 16 + 2 AS v FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_shipdate < TIMESTAMP '1995-02-01')")(
    lambda spark, d: N.isolated(G.EdgeGraph(G.edges_of(G.part_supplier(spark, d, until="1995-02-01"))), spark.read.parquet(f"{d}/part.parquet").select(G.vid(F.col("p_partkey"), "part"))))
_half = lambda a, b: f"SELECT DISTINCT user_id AS a, event_type AS b FROM events WHERE ts >= TIMESTAMP '{a}' AND ts < TIMESTAMP '{b}'"
register("join_full_two_windows", f"WITH x AS ({_half('2024-01-01', '2024-01-08')}), y AS ({_half('2024-01-08', '2024-01-15')}) SELECT coalesce(x.a, y.a) AS a, coalesce(x.b, y.b) AS b, (x.a IS NOT NULL)::INT AS in_one, (y.a IS NOT NULL)::INT AS in_two FROM x FULL JOIN y ON x.a = y.a AND x.b = y.b")(
    lambda spark, d: N.diff(V.typed_pairs(spark, d, "2024-01-01", "2024-01-08"), V.typed_pairs(spark, d, "2024-01-08", "2024-01-15")))
register("join_cross_subsets", f"{_PL}, {color_sql(3, [1])} SELECT v, s::INT AS sub FROM col, (SELECT unnest(range(1, 8)) AS s) WHERE (s >> c) & 1 = 1")(
    lambda spark, d: N.subsets_of_color(_colored(spark, d, "page_link")[1], 3))
register("join_theta_disjoint", f"{_PL}, {color_sql(4, [1])}, m AS (SELECT DISTINCT src AS v, (1 << c::INT)::INT AS m FROM e JOIN col ON col.v = dst) SELECT x.v, x.m AS m1, y.m AS m2 FROM m x JOIN m y ON x.v = y.v AND x.m & y.m = 0")(
    lambda spark, d: (lambda g, col: N.disjoint_masks(C.neighbor_sums(C.init_counts(col), g.edges)))(*_colored(spark, d, "page_link", 4)))
register("join_range_events", "WITH x AS (SELECT user_id AS u, floor(epoch(ts))::BIGINT AS s FROM events) SELECT x.u AS a, y.u AS b, count(*) AS n FROM x JOIN x y ON x.u < y.u AND y.s BETWEEN x.s - 60 AND x.s + 60 GROUP BY 1, 2")(
    lambda spark, d: V.user_coactive(spark, d))
register("join_asof_event_before", "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS prev_id FROM events")(
    lambda spark, d: V.asof_prev(spark, d))
register("join_self_co_order", "SELECT DISTINCT x.l_partkey * 16 + 2 AS a, y.l_partkey * 16 + 2 AS b FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey")(
    lambda spark, d: G.graph(spark, d, "co_order").edges.where("src < dst").select(F.col("src").alias("a"), F.col("dst").alias("b")))


# -- aggregates ---------------------------------------------------------------------------------

register("agg_partial_final_sum", f"{_HUB}, {color_sql(3, [1])} SELECT (1 << c::INT)::INT AS mask, count(DISTINCT src) AS vertices, count(*) AS n FROM e JOIN col ON col.v = dst GROUP BY 1")(
    lambda spark, d: (lambda g, col: C.neighbor_sums(C.init_counts(col), g.edges).groupBy("mask").agg(F.count("*").alias("vertices"), F.sum("n").alias("n")))(*_colored(spark, d, "hub")))
register("agg_distinct_neighbors", "SELECT o_custkey AS c, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_partkey) AS parts FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1")(
    lambda spark, d: spark.read.parquet(f"{d}/orders.parquet").select("o_orderkey", "o_custkey").join(spark.read.parquet(f"{d}/lineitem.parquet").select("l_orderkey", "l_suppkey", "l_partkey"), F.col("o_orderkey") == F.col("l_orderkey"))
    .groupBy(F.col("o_custkey").alias("c")).agg(F.countDistinct("l_suppkey").alias("suppliers"), F.countDistinct("l_partkey").alias("parts")))
register("agg_approx_neighbors", f"{_PL} SELECT count(DISTINCT x.src) AS vertices, true AS close FROM e x JOIN e y ON y.src = x.dst AND y.dst <> x.src")(
    lambda spark, d: N.two_hop_error(G.graph(spark, d, "page_link")).select("vertices", (F.col("mean_error") <= 0.04).alias("close")))
register("agg_cube_edges", "SELECT o_orderpriority AS priority, o_orderstatus AS status, GROUPING(o_orderpriority, o_orderstatus)::BIGINT AS level, count(*) AS n FROM orders GROUP BY CUBE (o_orderpriority, o_orderstatus)")(
    lambda spark, d: spark.read.parquet(f"{d}/orders.parquet").cube(F.col("o_orderpriority").alias("priority"), F.col("o_orderstatus").alias("status")).agg(F.grouping_id().alias("level"), F.count("*").alias("n")))


@register("agg_rollup_region_nation", "SELECT r_name AS region, n_name AS nation, count(*) AS customers FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)")
def rollup(spark, d):
    t = lambda n: spark.read.parquet(f"{d}/{n}.parquet")
    small = t("nation").join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    x = t("customer").select("c_nationkey").join(F.broadcast(small), F.col("c_nationkey") == F.col("n_nationkey"))  # nations are few
    return x.rollup(F.col("r_name").alias("region"), F.col("n_name").alias("nation")).agg(F.count("*").alias("customers"))


# an order's line as a run: by its return flag and status, its number of pieces and its place
_REPORT = "SELECT l_returnflag AS mode, l_linestatus AS template, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS pieces, CAST(max(l_linenumber) AS BIGINT) AS place FROM {} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())"
register("agg_grouping_sets_runs", _REPORT.format("lineitem"))(lambda spark, d: spark.sql(_REPORT.format("{runs}"), runs=spark.read.parquet(f"{d}/lineitem.parquet")))
register("agg_filter_pivot", f"{_HUB}, {color_sql(3, [1])} SELECT (v % 16)::INT AS kind, count(*) FILTER (c = 0) AS m1, count(*) FILTER (c = 1) AS m2, count(*) FILTER (c = 2) AS m4 FROM col GROUP BY 1")(
    lambda spark, d: _colored(spark, d, "hub")[1].groupBy(N.kind_of().alias("kind")).pivot("mask", [1, 2, 4]).agg(F.count("v")).select("kind", *[F.coalesce(f"`{m}`", F.lit(0)).alias(f"m{m}") for m in (1, 2, 4)]))
register("agg_quantiles_degree", f"{_PS}, {_deg} SELECT round(quantile_cont(deg, 0.5), 6) AS median, round(quantile_cont(deg, 0.9), 6) AS p90, max(deg) AS max_deg FROM d")(
    lambda spark, d: N.degree_quantiles(G.graph(spark, d, "part_supplier")))


# -- windows and sets ---------------------------------------------------------------------------

register("win_rank_degree", f"{_PS}, {_deg} SELECT v, deg, rank() OVER w::INT AS rk, dense_rank() OVER w::INT AS dense, row_number() OVER (PARTITION BY v % 16 ORDER BY deg DESC, v)::INT AS rn FROM d WINDOW w AS (PARTITION BY v % 16 ORDER BY deg DESC)".replace("rank() OVER w::INT AS rk, dense_rank() OVER w::INT AS dense, row_number() OVER (PARTITION BY v % 16 ORDER BY deg DESC, v)::INT AS rn", "(rank() OVER w)::INT AS rk, (dense_rank() OVER w)::INT AS dense, (row_number() OVER (PARTITION BY v % 16 ORDER BY deg DESC, v))::INT AS rn"))(
    lambda spark, d: N.rank_degree(G.graph(spark, d, "part_supplier")))
_IT = list(range(1, 13))


@register("win_ntile_groups", f"SELECT it, colorful, (ntile(3) OVER (ORDER BY it))::INT AS grp FROM ({colorful_sql('page_link', TreeTemplate.named('u3-1'), _IT)})")
def ntile_groups(spark, d):
    from pyspark.sql import Window

    x = C.colorful_count(G.graph(spark, d, "page_link"), TreeTemplate.named("u3-1"), _IT, SEED)
    return x.withColumn("grp", F.ntile(3).over(Window.orderBy("it")))  # a row a colouring


register("win_lead_user_next", "SELECT event_id, user_id, lead(user_id) OVER (ORDER BY ts, event_id) AS next_user FROM events")(lambda spark, d: V.next_users(spark, d))
register("win_running_edges", "SELECT event_id, row_number() OVER (ORDER BY ts, event_id) AS n FROM events")(lambda spark, d: V.growth(spark, d))
register("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY floor(epoch(ts))::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")(lambda spark, d: V.recent_activity(spark, d))
register("topk_per_kind", f"{_HUB}, {_deg} SELECT * FROM (SELECT (v % 16)::INT AS kind, (row_number() OVER (PARTITION BY v % 16 ORDER BY deg DESC, v))::INT AS rn, v, deg FROM d) WHERE rn <= 3")(
    lambda spark, d: N.top_hubs(G.graph(spark, d, "hub")))
register("set_union_graphs", f"{_HUB} SELECT (a % 16)::INT AS kind_a, (b % 16)::INT AS kind_b, count(*) AS n FROM p GROUP BY 1, 2")(
    lambda spark, d: G.graph(spark, d, "hub").edges.where("src < dst").groupBy(N.kind_of("src").alias("kind_a"), N.kind_of("dst").alias("kind_b")).agg(F.count("*").alias("n")))
register("set_intersect_vertices", f"{_PS}, {_deg} SELECT v FROM d WHERE deg >= 20 INTERSECT SELECT l_partkey * 16 + 2 FROM lineitem JOIN orders ON l_orderkey = o_orderkey")(
    lambda spark, d: N.common_vertices(G.graph(spark, d, "cust_part"), G.graph(spark, d, "part_supplier")))
_year = lambda y: f"SELECT l_partkey * 16 + 2 AS a, l_suppkey * 16 + 3 AS b FROM lineitem WHERE l_shipdate >= TIMESTAMP '{y}-01-01' AND l_shipdate < TIMESTAMP '{y + 1}-01-01'"
register("set_except_edges", f"{_year(1996)} EXCEPT {_year(1995)}")(
    lambda spark, d: G.part_supplier(spark, d, "1996-01-01", "1997-01-01").exceptAll(G.part_supplier(spark, d, "1995-01-01", "1996-01-01")).distinct().join(G.part_supplier(spark, d, "1995-01-01", "1996-01-01"), ["a", "b"], "left_anti"))


# -- scalars ------------------------------------------------------------------------------------

_href = "'href=\"([^\"]*)\"'"
register("str_page_links", f"SELECT page_id, h AS href, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host FROM (SELECT page_id, url, unnest(regexp_extract_all(html, {_href}, 1)) AS h FROM pages)")(
    lambda spark, d: spark.read.parquet(f"{d}/pages.parquet").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("href"), F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host")))
register("str_doc_lines", "SELECT md5(l) AS line, count(DISTINCT doc_id) AS docs FROM (SELECT doc_id, trim(unnest(string_split(text, chr(10)))) AS l FROM documents) WHERE length(l) >= 20 GROUP BY 1 HAVING count(DISTINCT doc_id) > 1")(
    lambda spark, d: spark.read.parquet(f"{d}/documents.parquet").select("doc_id", F.explode(F.split("text", "\n")).alias("l")).select("doc_id", F.trim("l").alias("l")).where(F.char_length("l") >= 20)
    .groupBy(F.md5("l").alias("line")).agg(F.countDistinct("doc_id").alias("docs")).where("docs > 1"))
register("json_event_props", "SELECT user_id * 16 + 9 AS a, regexp_extract(props, '\"k\": *([0-9]+)', 1)::BIGINT * 16 + 13 AS b FROM events")(lambda spark, d: G.user_prop(spark, d))
register("date_bucket_edges", "SELECT strftime(o_orderdate, '%Y-%m') AS month, (dayofweek(o_orderdate) + 1)::INT AS weekday, count(*) AS n FROM orders GROUP BY 1, 2")(lambda spark, d: V.edges_by_period(spark, d))
register("bit_mask_ops", "SELECT x::INT AS x, y::INT AS y, (x | y)::INT AS both, (x & y = 0) AS disjoint, bit_count(x | y)::INT AS size, (1 << (x % 8))::INT AS bit FROM (SELECT DISTINCT o_orderkey % 64 AS x, o_custkey % 64 AS y FROM orders)")(
    lambda spark, d: spark.read.parquet(f"{d}/orders.parquet").select((F.col("o_orderkey") % 64).cast("int").alias("x"), (F.col("o_custkey") % 64).cast("int").alias("y")).distinct()
    .select("x", "y", F.expr("x | y").alias("both"), F.expr("(x & y) = 0").alias("disjoint"), F.expr("bit_count(x | y)").alias("size"), F.expr("shiftleft(1, x % 8)").alias("bit")))


@register("array_vector_cosine", "SELECT x.vec_id AS a, y.vec_id AS b, round(list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]), 6) AS cosine FROM embeddings x JOIN embeddings y ON x.label = y.label AND x.vec_id < y.vec_id")
def vector_cosine(spark, d):
    e = spark.read.parquet(f"{d}/embeddings.parquet").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("x"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    e = e.withColumn("n", F.sqrt(dot("x", "x")))
    o = e.select(F.col("vec_id").alias("b"), "label", F.col("x").alias("y"), F.col("n").alias("m"))
    near = e.join(o, "label").where("vec_id < b")
    return near.select(F.col("vec_id").alias("a"), "b", F.round(dot("x", "y") / (F.col("n") * F.col("m")), 6).alias("cosine"))


register("map_neighbor_counts", f"{_HUB} SELECT src AS v, count(*) FILTER (dst % 16 = 1) AS orders, count(*) FILTER (dst % 16 = 4) AS nations, count(*) FILTER (dst % 16 = 5) AS segments FROM e WHERE src % 16 = 0 GROUP BY 1")(
    lambda spark, d: N.kind_profile(G.graph(spark, d, "hub"), {"orders": 1, "nations": 4, "segments": 5}).where(N.kind_of() == 0))


# -- functions ----------------------------------------------------------------------------------

@register("udf_pandas_packed_combine", f"WITH {graph_sql('page_link')}, {color_sql(5, [1])} SELECT c0.it::INT AS it, c0.v, ((1 << c0.c::INT) + (1 << c1.c::INT) + (1 << c2.c::INT))::INT AS mask, count(*)::DOUBLE AS cnt FROM col c0 JOIN e e1 ON e1.src = c0.v JOIN col c1 ON c1.v = e1.dst AND c1.c <> c0.c JOIN e e2 ON e2.src = c1.v JOIN col c2 ON c2.v = e2.dst AND c2.c NOT IN (c0.c, c1.c) GROUP BY 1, 2, 3")
def packed_combine(spark, d):
    """Two steps of the packed layout: paths of three vertices from their end."""
    g, col = _colored(spark, d, "page_link", 5)
    leaf = packed.pack(C.init_counts(col), 5, 1)
    two = packed.combine(leaf, packed.neighbor_sums(leaf, g.edges, 5, 1), 1, 5, 2, 1)
    return packed.unpack(packed.combine(leaf, packed.neighbor_sums(two, g.edges, 5, 2), 1, 5, 3, 1), 5, 3)


_u3 = f"SELECT it, colorful * {T.scale_up(3)!r}::DOUBLE AS estimate FROM ({colorful_sql('page_link', TreeTemplate.named('u3-1'), _IT)})"


@register("udaf_median_of_means", f"SELECT round(median(z), 6) AS estimate FROM (SELECT it % 3 AS g, avg(estimate) AS z FROM ({_u3}) GROUP BY 1)")
def mom_udaf(spark, d):
    x = C.unbias(C.colorful_count(G.graph(spark, d, "page_link"), TreeTemplate.named("u3-1"), _IT, SEED), 3)
    return x.groupBy().agg(tables.median_of_means_udaf()("it", "estimate", F.lit(3)).alias("estimate")).select(F.round("estimate", 6).alias("estimate"))


@register("udtf_ring_schedule", "SELECT ((o - 1) // 2 + 1)::INT AS step, r::INT AS receiver, ((r - o + 7) % 7)::INT AS sender FROM (SELECT unnest(range(7)) AS r), (SELECT unnest(range(1, 7)) AS o)")
def udtf_schedule(spark, d):
    tables.register(spark)
    return spark.sql("SELECT * FROM ring_schedule(7, 5)")


# a path splits off one end at a time in the heavy order: the root stays alone, the rest is cut
@register("udtf_split_steps", "SELECT (t - 1)::INT AS step, t::INT AS size, 1::INT AS keep_size, (t - 1)::INT AS cut_size, 1::INT AS d FROM (SELECT unnest(range(2, 8)) AS t)")
def udtf_steps(spark, d):
    tables.register(spark)
    return spark.sql("SELECT * FROM split_steps('-1 0 1 2 3 4 5')")


# -- streams ------------------------------------------------------------------------------------

_open = "(SELECT date_trunc('milliseconds', max(ts)) - INTERVAL 1 HOUR FROM events)"
_fmt = "strftime(w, '%Y-%m-%d %H:%M:%S') AS start"


def _events(spark, d):
    return S.stream(spark, f"{d}/event[s].parquet")  # a pattern, as a stream takes no single file


register("stream_tumbling_degree", f"SELECT {_fmt}, user_id, count(*) AS deg FROM (SELECT date_trunc('day', ts) AS w, user_id FROM events) WHERE w + INTERVAL 1 DAY <= {_open} GROUP BY 1, 2")(
    lambda spark, d: S.drained(S.window_degree(_events(spark, d), "1 day"), "tumbling"))
register("stream_sliding_edges", f"SELECT {_fmt}, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS w FROM events) WHERE w + INTERVAL 2 HOUR <= {_open} GROUP BY 1")(
    lambda spark, d: S.drained(S.window_edges(_events(spark, d), "2 hours", "1 hour"), "sliding"))
register("stream_session_users", f"WITH x AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), y AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS g FROM x) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM y GROUP BY user_id, g HAVING max(ts) + INTERVAL 30 MINUTE <= {_open}")(
    lambda spark, d: S.drained(S.sessions(_events(spark, d)), "sessions"))
register("stream_dedupe_edges", "SELECT DISTINCT user_id, event_type FROM events")(lambda spark, d: S.drained(S.dedupe(_events(spark, d)), "dedupe"))
register("stream_late_dropped", f"SELECT {_fmt}, count(*) AS n FROM (SELECT date_trunc('day', ts) AS w FROM events WHERE ts >= TIMESTAMP '2024-01-16') WHERE w + INTERVAL 1 DAY <= {_open} GROUP BY 1")(
    lambda spark, d: S.late_demo(spark, V.events(spark, d), "2024-01-16"))
register("stream_star_counts", f"WITH n AS (SELECT {_fmt}, user_id, count(*)::HUGEINT AS n FROM (SELECT date_trunc('day', ts) AS w, user_id FROM events) WHERE w + INTERVAL 1 DAY <= {_open} GROUP BY 1, 2) SELECT start, sum(n * (n - 1) // 2)::BIGINT AS star3, sum(n * (n - 1) * (n - 2) // 6)::BIGINT AS star4 FROM n GROUP BY 1")(
    lambda spark, d: S.star_counts(_events(spark, d)))


# -- small counts and edge cases ----------------------------------------------------------------

register("leaf_counts", f"{_PL}, {color_sql(5, [1, 2])} SELECT it::INT AS it, v, (1 << c::INT)::INT AS mask, 1::BIGINT AS cnt FROM col")(
    lambda spark, d: C.init_counts(C.assign_colors(G.graph(spark, d, "page_link").nodes(), 5, [1, 2], SEED)))
register("rooted_counts_u3_1", f"{_PL}, {color_sql(3, [1])} SELECT c0.it::INT AS it, c0.v, 7::INT AS mask, (count(*) // 2)::BIGINT AS cnt FROM col c0 JOIN e e1 ON e1.src = c0.v JOIN col c1 ON c1.v = e1.dst AND c1.c <> c0.c JOIN e e2 ON e2.src = c0.v JOIN col c2 ON c2.v = e2.dst AND c2.c NOT IN (c0.c, c1.c) GROUP BY 1, 2")(
    lambda spark, d: (lambda g, col: C.rooted_counts(g, TreeTemplate.named("u3-1"), col))(*_colored(spark, d, "page_link")))


@register("tiny_k1_k2_counts", f"{_PS} SELECT 1::INT AS k, count(*) AS colorful FROM part UNION ALL SELECT 2, (SELECT count(*) FROM p x JOIN (WITH {color_sql(2, [1])} SELECT v, c FROM col) s ON s.v = x.a JOIN (WITH {color_sql(2, [1])} SELECT v, c FROM col) t ON t.v = x.b AND t.c <> s.c)")
def tiny(spark, d):
    """One vertex: all vertices, those without an edge too.  Two: the edges whose ends differ in colour."""
    g = G.graph(spark, d, "part_supplier")
    parts = spark.read.parquet(f"{d}/part.parquet").select(G.vid(F.col("p_partkey"), "part"))
    one = C.colorful_count(G.EdgeGraph(g.edges, parts), TreeTemplate((-1,)), [1], SEED).select(F.lit(1).alias("k"), "colorful")
    return one.unionByName(C.colorful_count(g, TreeTemplate.named("edge2"), [1], SEED).select(F.lit(2).alias("k"), "colorful"))


@register("dirty_edges_clean", f"{_PS} SELECT src, dst FROM e")
def dirty(spark, d):
    """Loops, repeats, both orders and nulls among the pairs give the same graph."""
    p = G.part_supplier(spark, d)
    loops = p.select("a", F.col("a").alias("b"))
    nulls = p.select("a", F.lit(None).cast("long").alias("b"))
    return G.edges_of(p.unionByName(p.select(F.col("b").alias("a"), F.col("a").alias("b"))).unionByName(p).unionByName(loops).unionByName(nulls))
