import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from treecount.operators import counting as C
from treecount.operators import exact as X
from treecount.operators import exchange as E
from treecount.plans import templates as T
from treecount.plans.templates import TreeTemplate
from treecount.sources.graphs import EdgeGraph, edges_of

K4 = list(itertools.combinations(range(1, 5), 2))
C6 = [(i, i % 6 + 1) for i in range(1, 7)]


def graph(spark, pairs):
    return EdgeGraph(edges_of(spark.createDataFrame(pairs, "a long, b long")))


def brute(pairs, t):
    near = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    n = sum(all(m[b] in near[m[a]] for a, b in t.edges) for m in itertools.permutations(sorted(near), t.k))
    return n // t.automorphisms


#: Fixed published terms: memory, work.
TERMS = {"u3-1": (3, 6), "u5-2": (25, 70), "u7-2": (147, 434), "u10-2": (1047, 5610), "u12-1": (4082, 24552), "u12-2": (3135, 38016), "u13": (4823, 109603), "u14": (7371, 242515), "u15-1": (12383, 753375), "u15-2": (15773, 617820)}


def test_published_terms():
    assert {n: (T.memory_terms(TreeTemplate.named(n)), T.work_terms(TreeTemplate.named(n))) for n in T.PUBLISHED} == TERMS


def test_symmetries_split_into_steps_and_root():
    for n in T.CATALOGUE:
        t = TreeTemplate.named(n)
        plan = T.split_plan(t, share=False)
        assert math.prod(s.d for s in plan.steps) * plan.root_orbit == t.automorphisms


def test_free_trees():
    assert [len(T.all_free_trees(k)) for k in range(1, 8)] == [1, 1, 1, 2, 3, 6, 11]


def test_no_tree_is_refused():
    for bad in ((0,), (-1, 2, 1), ()):
        with pytest.raises(ValueError):
            TreeTemplate(bad)
    with pytest.raises(ValueError):
        TreeTemplate.from_edges([(0, 1), (1, 2), (2, 0)])


@pytest.mark.parametrize("pairs", [K4, C6])
def test_average_over_all_colourings_is_exact(spark, pairs):
    t = TreeTemplate.named("u3-1")
    g = graph(spark, pairs)
    ids = sorted({x for p in pairs for x in p})
    rows = [(i, v, 1 << c) for i, cs in enumerate(itertools.product(range(3), repeat=len(ids))) for v, c in zip(ids, cs)]
    counts = C.rooted_counts(g, t, spark.createDataFrame(rows, "it int, v long, mask int"))
    total = counts.where("mask = 7").agg(F.sum("cnt")).first()[0]
    assert total * T.scale_up(3) / 3 ** len(ids) == pytest.approx(brute(pairs, t))


@pytest.mark.parametrize("name", ["u3-1", "path4", "star4", "fork5"])
def test_joins_and_closed_forms(spark, name):
    t = TreeTemplate.named(name)
    pairs = [*K4, (4, 5), (5, 6), (2, 6)]
    g = graph(spark, pairs)
    assert X.exact_by_joins(g, t).first()[0] == brute(pairs, t)
    if name == "path4":
        assert X.exact_path4(g).first()[0] == brute(pairs, t)
    if name == "star4":
        assert X.exact_star(g, 4).first()[0] == brute(pairs, t)


def test_all_modes_agree(spark):
    t, g = TreeTemplate.named("fork5"), graph(spark, [*K4, (4, 5), (5, 6), (2, 6), (6, 7), (7, 8), (3, 8)])
    want = sorted(map(tuple, X.signed_subset_count(g, t, C.assign_colors(g.nodes(), 5, [1, 2, 3])).collect()))
    for mode in C.MODES:
        assert sorted(map(tuple, C.colorful_count(g, t, [1, 2, 3], mode=mode, threshold=4).collect())) == want, mode
    for how in ({"combine_by": "residual"}, {"combine_by": "table"}, {"combine_by": "packed"}, {"order": "light"}, {"order": "best"}, {"root": 3}, {"share": False}, {"mode": "staged", "overlap": False}, {"mode": "adaptive_split", "s": 1, "threshold": 0}):
        assert sorted(map(tuple, C.colorful_count(g, t, [1, 2, 3], **how).collect())) == want, how


def test_counts_beyond_64_bits(spark):
    n = 600
    both = edges_of(spark.range(n * n).select((F.col("id") % n).alias("a"), (F.floor(F.col("id") / n) + n).alias("b")))
    g, t = E.stored(EdgeGraph(both)), TreeTemplate.star(8)
    assert C.count_type_for(g, 8) == "decimal" and C.count_type_for(g, 3) == "long" and C.count_type_for(g, 12) == "double"
    got = {k: C.colorful_count(g, t, [1], count_type=k).first()["colorful"] for k in ("decimal", "double", "auto")}
    colors = {r.v: r.mask for r in C.assign_colors(g.nodes(), 8, [1]).collect()}
    side = [[sum(m == 1 << c for v, m in colors.items() if (v < n) == low) for c in range(8)] for low in (True, False)]
    # a centre on one side, a leaf of every other colour on the other
    want = sum(side[s][c] * math.prod(side[1 - s][x] for x in range(8) if x != c) for s in (0, 1) for c in range(8))
    assert int(got["decimal"]) == want == int(got["auto"]) and got["double"] == pytest.approx(want, rel=1e-9)
    big = spark.createDataFrame([(1, 2, 1, 2**62), (1, 3, 1, 2**62)], "it int, v long, mask int, cnt long")
    with pytest.raises(Exception, match="OVERFLOW"):
        C.neighbor_sums(big, spark.createDataFrame([(1, 2), (1, 3)], "src long, dst long")).collect()


@pytest.mark.parametrize("name", ["u13", "u14", "u15-1", "u15-2"])
def test_largest_templates_equal_the_signed_sum(spark, name):
    rng, t = np.random.default_rng(8), TreeTemplate.named(name)
    pairs = [(i, (i + j) % 26) for i in range(26) for j in (1, 2)] + [tuple(map(int, rng.choice(26, 2, False))) for _ in range(12)]
    g = graph(spark, pairs)
    near = np.zeros((26, 26), np.int64)
    for a, b in pairs:
        near[a, b] = near[b, a] = 1
    color = {v: 1 << v % t.k for v in range(26)}
    subsets = np.arange(1 << t.k)
    base = np.stack([(subsets & color[v]) > 0 for v in range(26)], 1).astype(np.int64)

    def maps(node):
        out = base
        for p, child in t.edges:
            if p == node:
                out = out * (maps(child) @ near)
        return out

    sign = np.array([(-1) ** (t.k - m.bit_count()) for m in range(1 << t.k)])
    want = int((maps(0).sum(1) * sign).sum()) // t.automorphisms
    counts = C.rooted_counts(g, t, spark.createDataFrame([(1, v, m) for v, m in color.items()], "it int, v long, mask int"))
    full = counts.where(F.expr(f"bit_count(mask) = {t.k}")).agg(F.sum("cnt")).first()[0]
    assert full // T.split_plan(t).root_orbit == want and want > 0


def test_switch_keeps_small_templates_in_one_exchange():
    small, large = TreeTemplate.named("u5-2"), TreeTemplate.named("u10-2")
    for switch in ("size", "intensity", "cost"):
        assert not any(C.is_large(x, small, switch) for x in T.split_plan(small).steps), switch
        assert any(C.is_large(x, large, switch) for x in T.split_plan(large).steps), switch
    assert all(C.is_large(x, small, threshold=0) for x in T.split_plan(small).steps)


def test_samples_are_complete_and_sound(spark):
    pairs = [*K4, (4, 5), (5, 6), (2, 6), (6, 7)]
    g, t = graph(spark, pairs), TreeTemplate.named("fork5")
    near = {frozenset(p) for p in pairs}
    color = {r.v: r.mask for r in C.assign_colors(g.nodes(), 5, [1]).collect()}
    parents = C.walk_parents(t)
    every = {m for m in itertools.permutations(range(1, 8), 5) if all(p < 0 or frozenset((m[i], m[p])) in near for i, p in enumerate(parents)) and len({color[v] for v in m}) == 5}
    rows = {tuple(r) for r in C.sample_embeddings(g, t, 1000).collect()}
    assert rows == every and every
    few = {tuple(r) for r in C.sample_embeddings(g, t, 3).collect()}
    assert len(few) == min(3, len(every)) and few <= every


def test_four_cycles(spark):
    pairs = [*K4, (4, 5), (5, 6), (2, 6), (6, 7), (7, 8), (3, 8)]
    near = {frozenset(p) for p in pairs}
    want = sum(all(frozenset((m[i], m[i - 1])) in near for i in range(4)) for m in itertools.permutations(range(1, 9), 4)) // 8
    assert X.four_cycles(graph(spark, pairs)).first()[0] == want


def test_tags_refuse_what_does_not_fit(spark):
    tag = lambda a, b, c: spark.range(1).select(E.pack_tag(F.lit(a), F.lit(b), F.lit(c)).alias("t")).first()["t"]
    assert tag(1023, 1, 4095) & 0xFFFFFFFF == 1023 << 22 | 1 << 12 | 4095
    with pytest.raises(Exception, match="too large"):
        tag(1, 1024, 0)


def test_a_local_folder_serves_one_machine_only(spark, monkeypatch):
    assert E.work_folder(spark)
    cluster = type("S", (), {"conf": type("C", (), {"get": staticmethod(lambda *_: None)}), "sparkContext": type("X", (), {"master": "spark://host:7077", "applicationId": "a"})})
    with pytest.raises(ValueError):
        E.work_folder(cluster)


def test_dirty_edges(spark):
    dirty = [(1, 2), (2, 1), (1, 1), (1, 2), (None, 2), (2, 3)]
    assert sorted(map(tuple, graph(spark, dirty).edges.collect())) == [(1, 2), (2, 1), (2, 3), (3, 2)]


def test_tiny_templates_and_empty_graph(spark):
    g = graph(spark, K4)
    assert C.colorful_count(g, TreeTemplate((-1,)), [1]).first()["colorful"] == 4
    assert X.exact_by_joins(g, TreeTemplate((-1, 0))).first()[0] == 6
    empty = EdgeGraph(g.edges.where("false"))
    assert [tuple(r) for r in C.colorful_count(empty, TreeTemplate.named("path4"), [1]).collect()] == [(1, 0)]


def test_slices(spark):
    star = EdgeGraph(edges_of(spark.createDataFrame([(0, i) for i in range(1, 126)], "a long, b long")))
    n = C.split_neighbor_lists(star.edges.where("src = 0"), 50).groupBy("slot").count().collect()
    assert sorted(r["count"] for r in n) == [25, 50, 50]


def test_schedule(spark):
    for p, m in ((5, 3), (7, 5), (2, 3)):
        assert tuple(E.check_schedule(E.ring_schedule(spark, p, m), p).first()) == (p * (p - 1), 0, 0)


def test_worked_step(spark):
    keep = spark.createDataFrame([(1, 1, 0b00011, 2), (1, 1, 0b00101, 1)], "it int, v long, mask int, cnt long")
    cut = spark.createDataFrame([(1, 2, 0b11100, 2), (1, 2, 0b11010, 2)], "it int, v long, mask int, cnt long")
    edge = spark.createDataFrame([(1, 2)], "src long, dst long")
    for how in (C.extend_sumfirst, C.extend_edgewise):
        assert how(keep, cut, edge, 1).first()["cnt"] == 6


def test_number_of_colourings():
    n, t = T.n_colorings(3, 0.5, 0.1)
    assert t % 2 == 1 and n % t == 0 and n >= math.exp(3) * math.log(10) / 0.25


def test_estimates_use_all_colourings_of_eps_and_delta(spark, monkeypatch):
    from treecount.operators import counting, queries

    used = []

    def count(graph, template, its, *_, **__):
        used.append((template.k, len(its)))
        return spark.createDataFrame([(i, 1) for i in its], "it int, colorful long")

    monkeypatch.setattr(counting, "colorful_count", count)
    monkeypatch.setattr(counting, "written", lambda df, name: df)
    monkeypatch.setattr(queries.G, "graph", lambda *_: graph(spark, K4))
    r = queries.QUERIES["estimate_tree_count_u3_1"](spark, None).first()
    assert r.n_iter == 186 and sum(n for _, n in used) == 186
    used.clear()
    queries.QUERIES["tree_frequencies_k4"](spark, None)
    assert sum(n for k, n in used if k == 4) == 2 * counting.n_colorings(4, 0.5, 0.05)[0]
    used.clear()
    queries.QUERIES["frequent_trees_k5"](spark, None)
    assert sum(n for k, n in used if k == 5) == 3 * counting.n_colorings(5, 0.5, 0.1 / 3)[0]


def test_wide_and_negative_ids(spark):
    wide = [(16 * i + 13, (i << 57) - 5) for i in range(-8, 8)]
    star, path = graph(spark, wide), graph(spark, [*wide, (2**62, 2**62 + 2**31 - 1), (2**62 + 2**31 - 1, -7), (-7, 11)])
    t = TreeTemplate.named("path4")
    assert not C.tree_exists(star, t, 0.1)
    # the first two vertices of the only path agree modulo the prime of the polynomial colours
    assert C.tree_exists(path, t, 0.01)
    colors = C.assign_colors(star.nodes(), 4, [1]).collect()
    acc = lambda v: [a := 0, *[a := (a * v + s) % C.PRIME for s in C.coefficients(4, 1, 42)]][-1] % 4
    assert {r.v: r.mask for r in colors} == {r.v: 1 << acc(r.v) for r in colors}


def test_exact_counts_take_decimals_where_64_bits_overflow(spark, monkeypatch):
    n, t = 600, TreeTemplate.star(10)
    g = E.stored(EdgeGraph(edges_of(spark.range(n * n).select((F.col("id") % n).alias("a"), (F.floor(F.col("id") / n) + n).alias("b")))))
    want = [tuple(map(int, r)) for r in C.colorful_count(g, t, [1], count_type="decimal").collect()]
    assert want[0][1] >= 2**63
    for limit in (C.LONG_LIMIT, math.inf):
        monkeypatch.setattr(C, "LONG_LIMIT", limit)
        out = C.colorful_count(g, t, [1], count_type="exact")
        assert [tuple(map(int, r)) for r in out.collect()] == want and dict(out.dtypes)["colorful"] == "decimal(38,0)"
    small = C.colorful_count(graph(spark, K4), TreeTemplate.named("path4"), [1, 2], count_type="exact")
    assert dict(small.dtypes)["colorful"] == "bigint" and sorted(small.collect()) == sorted(C.colorful_count(graph(spark, K4), TreeTemplate.named("path4"), [1, 2]).collect())


def test_copies_count_as_joins_do(spark, monkeypatch):
    pairs = [*K4, (4, 5), (5, 6), (2, 6), (6, 2**40), (2**40, 8), (3, 8)]
    t, its = TreeTemplate.named("fork5"), list(range(1, 30))
    want = sorted(map(tuple, C.colorful_count(graph(spark, pairs), t, its).collect()))
    assert sorted(map(tuple, C.colorful_count(graph(spark, pairs), t, its, mode="replicated").collect())) == want
    # as whole numbers where doubles would not be exact: a centre with three leaves among n of each colour
    n = 300_000
    g = EdgeGraph(edges_of(spark.range(1, n).select(F.lit(0).alias("a"), F.col("id").alias("b"))))
    star = TreeTemplate.named("star4")
    assert C.colorful_count(g, star, [1], mode="replicated").first() == C.colorful_count(g, star, [1]).first()
    few = lambda m: C.estimate_tree_count(graph(spark, pairs), TreeTemplate.named("u3-1"), 1.0, 0.1, mode=m).first()
    got = [few("auto"), few("bulk")]
    monkeypatch.setattr(C, "COPY_EDGES", 5)
    got.append(few("auto"))
    assert list(got[0]) == pytest.approx(list(got[1])) and list(got[0]) == pytest.approx(list(got[2]))


def test_stars_beyond_64_bits(spark):
    n = 4_000_000
    star = EdgeGraph(spark.range(1, n + 1).select(F.lit(0).cast("long").alias("src"), F.col("id").alias("dst")))
    assert int(X.exact_star(star, 4).first()[0]) == math.comb(n, 3) > 2**63
    assert dict(X.exact_star(graph(spark, K4), 4).dtypes) == {"exact": "bigint"} and X.exact_star(graph(spark, K4), 4).first()[0] == 4


def test_paths_of_five(spark, monkeypatch):
    from treecount.operators import measure_queries

    monkeypatch.setattr(X, "exact_by_joins", None)  # the query lists no paths
    for pairs in (K4, [*K4, (4, 5), (5, 6), (2, 6), (6, 7), (7, 8), (3, 8), (3, 5)], list(itertools.combinations(range(7), 2)), [(1, 2)]):
        monkeypatch.setattr(measure_queries.G, "graph", lambda *_, p=pairs: graph(spark, p))
        row = measure_queries.QUERIES["exact_u5_2_knn"](spark, None)
        assert row.first()[0] == brute(pairs, TreeTemplate.named("u5-2")) and dict(row.dtypes) == {"exact": "bigint"}


def test_common_neighbours_in_tasks(spark, monkeypatch):
    from treecount.operators import blocks

    rng = np.random.default_rng(3)
    # a random graph, two hubs and ids far apart
    pairs = {(int(a), int(b)) for a, b in rng.integers(0, 60, (500, 2)) if a < b} | {(7, i) for i in range(100, 400)} | {(9, i) for i in range(100, 400, 2)} | {(3, 10**12), (5, 10**12), (-4, 3), (-4, 5)}
    ids = sorted({x for p in pairs for x in p})
    m = np.zeros((len(ids), len(ids)), np.int64)
    for a, b in pairs:
        if a != b:
            m[ids.index(a), ids.index(b)] = m[ids.index(b), ids.index(a)] = 1
    two, deg = m @ m, m.sum(1)
    tri = int(np.trace(two @ m)) // 6
    off = two - np.diag(np.diag(two))
    four = int((off * (off - 1)).sum()) // 8
    path = int((m * np.outer(deg - 1, deg - 1)).sum()) // 2 - 3 * tri
    g = graph(spark, sorted(pairs))
    for entries in (24_000_000, 900):
        monkeypatch.setattr(blocks, "ENTRIES", entries)
        assert X.triangles(g).first()[0] == tri and X.exact_path4(g).first()[0] == path and X.four_cycles(g).first()[0] == four
    empty = EdgeGraph(g.edges.where("src = 0 and src = 1"))
    assert X.triangles(empty).first()[0] == X.exact_path4(empty).first()[0] == X.four_cycles(empty).first()[0] == 0


def test_wedges_are_not_listed(spark):
    n = 500  # 3.1e10 paths of four in a complete graph, 6e7 pairs of neighbours
    g = EdgeGraph(spark.range(n * n).select(F.expr(f"id div {n}").alias("src"), (F.col("id") % n).alias("dst")).where("src <> dst"))
    assert X.exact_by_joins(g, TreeTemplate.named("path4")).first()[0] == n * (n - 1) * (n - 2) * (n - 3) // 2
    assert X.triangles(g).first()[0] == math.comb(n, 3) and X.four_cycles(g).first()[0] == 3 * math.comb(n, 4)
    for f in (X.triangles, X.four_cycles, X.exact_path4):
        assert "Join" not in f(g)._jdf.queryExecution().toString()


def test_existence_starts_with_one_colouring(spark, monkeypatch):
    seen, real = [], C.assign_colors
    monkeypatch.setattr(C, "assign_colors", lambda v, k, its, *a, **kw: seen.append(len(its)) or real(v, k, its, *a, **kw))
    assert C.tree_exists(graph(spark, list(itertools.combinations(range(40), 2))), TreeTemplate.named("path4")) and seen[0] == 1
    seen.clear()
    # none in a star: as many colourings as the bound on a false no asks for
    assert not C.tree_exists(graph(spark, [(0, 1), (0, 2), (0, 3)]), TreeTemplate.named("path4"), 0.5)
    assert sum(seen) == math.ceil(math.log(2) * T.scale_up(4)) and max(seen) <= 8


def test_two_hop_neighbours_are_counted_in_tasks(spark, monkeypatch):
    from treecount.operators import blocks
    from treecount.operators import neighborhood as N

    rng = np.random.default_rng(5)
    pairs = {(int(a), 1000 + int(b)) for a, b in rng.integers(0, 200, (400, 2))} | {(i, 5000) for i in range(150)} | {(7000, 7001)}
    near = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    want = {a: len({z for m in near[a] for z in near[m]} - {a}) for a in near}
    g = graph(spark, sorted(pairs))
    for entries in (24_000_000, 500):
        monkeypatch.setattr(blocks, "ENTRIES", entries)
        assert {r[0]: r[1] for r in blocks.two_hop_counts(g.edges).collect()} == {a: n for a, n in want.items() if n}
    row = N.two_hop_error(g).first()
    assert row[0] == sum(n > 0 for n in want.values()) and row[1] <= 0.04


@pytest.mark.parametrize("name", ["u5-2", "u7-2", "fork5"])
def test_residues_of_many_blocks_equal_rows_of_counts(spark, monkeypatch, name):
    from treecount.operators import residues

    monkeypatch.setattr(residues, "NUMBERS", 300)
    monkeypatch.setattr(residues, "EDGES", 60)
    seen = []
    numbered = residues._numbered
    monkeypatch.setattr(residues, "_numbered", lambda e, root, blocks: (seen.append(blocks), numbered(e, root, blocks)))
    # ids below zero, a hub, and a vertex alone with one neighbour
    pairs = [*K4, *C6, *((0, -i) for i in range(1, 30)), *((i, -(i % 29) - 1) for i in range(1, 40)), (100, 101)]
    g, t = graph(spark, pairs), TreeTemplate.named(name)
    want = {r["it"]: int(r["colorful"]) for r in C.colorful_count(g, t, [1, 2], count_type="long").collect()}
    for mode in ("bulk", "adaptive_split"):
        got = C.colorful_count(g, t, [1, 2], mode=mode, count_type="decimal")
        assert got.schema["colorful"].dataType.simpleString() == "decimal(38,0)"
        assert {r["it"]: int(r["colorful"]) for r in got.collect()} == want
    assert min(seen) > 2 and max(want.values()) > 0


@pytest.mark.parametrize("name", ["u14", "u15-2"])
def test_widest_templates_need_no_rows_of_counts(spark, monkeypatch, name):
    from treecount.operators import residues

    pairs, t = [(i, (i + j) % 60) for i in range(60) for j in (1, 2, 5)] + [(0, i) for i in range(3, 50)], TreeTemplate.named(name)
    g = graph(spark, sorted({(min(p), max(p)) for p in pairs}))
    rows = C.colorful_count(g, t, [1], count_type="long").first()["colorful"]
    monkeypatch.setattr(residues, "LONG", 1)
    monkeypatch.setattr(C, "rooted_counts", lambda *a, **k: pytest.fail("rows of counts"))
    got = C.colorful_count(g, t, [1], count_type="exact")
    assert got.first()["colorful"] == rows > 0 and got.schema["colorful"].dataType.simpleString() == "bigint"


def test_paths_of_five_list_no_pairs_of_neighbours(spark, monkeypatch):
    from treecount.operators import blocks

    rng = np.random.default_rng(3)
    pairs = sorted({(min(p), max(p)) for p in rng.integers(0, 9, (22, 2)).tolist() if p[0] != p[1]})
    t = TreeTemplate.named("u5-2")
    want = brute(pairs, t)
    for entries in (24_000_000, 12):
        monkeypatch.setattr(blocks, "ENTRIES", entries)
        g = graph(spark, pairs)
        made, write = [], E.written
        monkeypatch.setattr(X, "written", lambda d, n: (made.append(n), write(d, n))[1])
        assert int(X.exact_path5(g).first()[0]) == want > 0
        # edges by ascending degree were joined with themselves
        assert "oriented" not in made


def test_counts_beyond_two_primes_are_whole(spark):
    """A star of seven with 20,000 leaves: a product of six colours' leaves beyond 64 bits, found without rows of counts."""
    t = TreeTemplate.star(7)
    g = EdgeGraph(edges_of(spark.range(1, 20_001).selectExpr("0 as a", "id as b")))
    n = {r["mask"]: r["n"] for r in C.assign_colors(g.nodes().where("v > 0"), 7, [1]).groupBy("mask").agg(F.count("*").alias("n")).collect()}
    own = C.assign_colors(g.nodes().where("v = 0"), 7, [1]).first()["mask"]
    want = math.prod(x for m, x in n.items() if m != own)
    with pytest.MonkeyPatch.context() as m:
        m.setattr(C, "rooted_counts", lambda *a, **k: pytest.fail("rows of counts"))
        assert int(C.colorful_count(g, t, [1], mode="adaptive_split", count_type="decimal").first()["colorful"]) == want > 1 << 63


def test_edges_and_their_shuffle_files_go_before_lists_are_sent(spark, monkeypatch):
    from treecount.operators import blocks

    made, gone, order = [], [], []
    for module in (blocks, X, E):
        write, drop = module.written, module.forget
        monkeypatch.setattr(module, "written", lambda d, n, w=write: (made.append((n, x := w(d, n))), x)[1])
        if hasattr(module, "forget"):
            monkeypatch.setattr(module, "forget", lambda d, f=drop: (gone.append(d._store_path), f(d))[1])
    free, send = blocks.release, blocks.over_pairs
    monkeypatch.setattr(blocks, "release", lambda s: (order.append("release"), free(s))[1])

    def sent(*a):
        order.append("sent")
        assert all(x._store_path in gone for n, x in made if n in ("edges", "ranked"))
        return send(*a)

    monkeypatch.setattr(blocks, "over_pairs", sent)
    g = lambda: graph(spark, K4)
    assert [f(g()).first()[0] for f in (X.triangles, X.four_cycles, X.exact_path4)] == [4, 3, 12]
    assert order == ["release", "release", "sent"] * 3 and {"edges", "ranked"} <= {n for n, _ in made}
