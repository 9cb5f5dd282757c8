"""Colour coding: colouring, the dynamic program over sub-templates, and the estimators.

Counts are rows (it, v, mask, cnt): colouring, vertex, set of colours as bits, number of colourful
occurrences.  Zero rows do not exist.  A step needs, for each vertex, the sum over its neighbours of
the cut part's counts; by distributivity the neighbour sum comes first (one join and one aggregation
with map-side combining), and the combination with the kept part is local to the vertex.

How the neighbour sums reach a vertex is the mode: all at once (``bulk``), in steps by ring distance
of vertex blocks (``staged``), by a choice for each sub-template (``adaptive``), and with long
neighbour lists cut into tasks (``adaptive_split``).  All modes give the same counts.
"""

from __future__ import annotations

import math
import time
from concurrent.futures import ThreadPoolExecutor
from decimal import Decimal

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import packed
from ..plans.templates import Shape, SplitStep, TreeTemplate, intensity, n_colorings, scale_up, split_plan
from ..sources.graphs import EdgeGraph
from . import residues
from .exchange import block_of, forget, narrowed, ring_offset, stored, written

PRIME = 2147483647
#: Pairs of colour sets tested for each disjoint one before a table of splits serves better.
PAIRS_PER_SPLIT = 16
#: Expected counts from which 64 bits are not tried.
LONG_LIMIT = 2.0**63
#: Colour sets of a table from which exact counts are not tried as rows of 64 bits.
ROWS_SETS = 1024
#: Largest graph that estimates copy to every task, in directed edges, and colours of vertices in one batch of joins.
COPY_EDGES = 2_000_000
BATCH_ROWS = 2_000_000
MODES = ("bulk", "staged", "adaptive", "adaptive_split", "edgewise", "local_remote", "disk_staged", "resident_bulk", "static_slots", "replicated")


# -- colouring ----------------------------------------------------------------------------------


def coefficients(k: int, it: int, seed: int) -> list[int]:
    s = (seed * 1000003 + it * 7919 + k) % PRIME
    out = []
    for _ in range(k):
        s = 48271 * s % PRIME
        out.append(s)
    return out


def assign_colors(vertices: DataFrame, k: int, iters: list[int], seed: int = 42, scheme: str = "poly", colors: int | None = None) -> DataFrame:
    """(it, v, mask): each vertex gets one of the colours in each colouring, by a hash, so reruns agree.

    ``poly`` is a random polynomial of degree k - 1 over a prime field: k-wise independent, for ids below
    2^31 - 1; wider ids count modulo the prime, so that two that agree there always share a colour.
    ``xxhash`` tells all ids apart.
    """
    c = colors or k
    if scheme == "xxhash":
        color = lambda it: F.pmod(F.xxhash64("v", F.lit(it), F.lit(seed)), F.lit(c))
    else:

        def color(it: int) -> Column:
            acc = F.lit(0).cast("long")
            v = F.pmod(F.col("v"), F.lit(PRIME))  # keeps the products of wide ids below 2^63
            for s in coefficients(k, it, seed):
                acc = (acc * v + F.lit(s)) % F.lit(PRIME)
            return acc % F.lit(c)

    # one array of all colourings of a vertex: no join with the list of colourings
    rows = F.array(*[F.struct(F.lit(it).alias("it"), F.call_function("shiftleft", F.lit(1), color(it).cast("int")).alias("mask")) for it in iters])
    return vertices.select("v", F.explode(rows).alias("x")).select("x.it", "v", "x.mask")


#: Column types of counts.  Long raises an error where it overflows; decimals are exact to 32 digits; doubles carry a
#: relative error of about the number of additions * 2^-53.
COUNT_TYPES = {"long": "long", "decimal": "decimal(38,0)", "double": "double"}


def init_counts(coloring: DataFrame, count_type: str = "long") -> DataFrame:
    """Counts of the single vertex: one, with the vertex's own colour."""
    return coloring.select("it", "v", "mask", F.lit(1).cast(COUNT_TYPES[count_type]).alias("cnt"))


def count_type_for(graph: EdgeGraph, k: int) -> str:
    """``long`` where no count can pass 63 bits, ``decimal`` up to 32 digits, ``double`` beyond: one aggregation of degrees.

    A tree of k vertices has at most V * D^(k-1) images, D the largest degree.
    """
    n = graph.edges.groupBy("src").agg(F.count("*").alias("n")).agg(F.count("*").alias("v"), F.max("n").alias("d")).first()
    bits = math.log2(max(n["v"] or 1, 1)) + (k - 1) * math.log2(max(n["d"] or 1, 1))
    return "long" if bits < 62 else "decimal" if bits < 105 else "double"


# -- one step -----------------------------------------------------------------------------------


def _total(value: Column, like: DataFrame, column: str) -> Column:
    """Sum in the type of a column; long and decimal sums raise an error where they overflow."""
    return F.sum(value).cast(like.schema[column].dataType)


def neighbor_sums(cut: DataFrame, edges: DataFrame) -> DataFrame:
    """(it, v, mask, n): for each vertex the sum of its neighbours' counts."""
    n = _total(F.col("cnt"), cut, "cnt").alias("n")
    c = cut.select("it", F.col("v").alias("dst"), "mask", "cnt")
    return edges.select("src", "dst").join(c, "dst").groupBy("it", F.col("src").alias("v"), "mask").agg(n)


def combine(keep: DataFrame, sums: DataFrame, d: int, sizes: tuple[int, int] | None = None) -> DataFrame:
    """Counts of the whole from the kept part's counts and the neighbour sums of the cut part."""
    k, s = keep.alias("k"), sums.alias("s")
    free = F.expr("(k.mask & s.mask) = 0")
    j = k.join(s, (F.col("k.it") == F.col("s.it")) & (F.col("k.v") == F.col("s.v")) & free)
    cnt = _total(F.col("k.cnt") * F.col("s.n"), keep, "cnt")
    out = j.groupBy("k.it", "k.v", F.expr("k.mask | s.mask").alias("mask")).agg(cnt.alias("cnt"))
    return _divided(out, d)


def combine_by_table(keep: DataFrame, sums: DataFrame, d: int, k: int, t: int, a: int) -> DataFrame:
    """As `combine`, with the exact pairs of colour sets from a table of fixed size instead of a test of all pairs."""
    spark = keep.sparkSession
    table = F.broadcast(split_table(spark, k, t, a))  # C(k,t) C(t,a) rows, at most a few million by k <= 15
    x = keep.join(table, keep["mask"] == table["m1"]).select("it", "v", "m2", "target", "cnt")
    j = x.join(sums.select("it", "v", F.col("mask").alias("m2"), "n"), ["it", "v", "m2"])
    out = j.groupBy("it", "v", F.col("target").alias("mask")).agg(_total(F.col("cnt") * F.col("n"), keep, "cnt").alias("cnt"))
    return _divided(out, d)


def combine_packed(keep: DataFrame, sums: DataFrame, d: int, k: int, t: int, a: int) -> DataFrame:
    """As `combine` with vector products over arrays of all colour sets; counts are doubles on the way."""
    x = packed.combine(packed.pack(keep, k, a), packed.pack(sums, k, t - a, "n"), d, k, t, a)
    return packed.unpack(x, k, t).withColumn("cnt", F.col("cnt").cast(keep.schema["cnt"].dataType))


def combined(keep: DataFrame, sums: DataFrame, step: SplitStep, k: int, how: str = "auto") -> DataFrame:
    """The step's combination: by testing all pairs of colour sets at a vertex (``residual``), by the ``table`` of splits, or ``packed``.

    ``auto`` tests pairs while a fair share of them is disjoint, and looks the splits up beyond.
    """
    t, a, b = step.sizes
    if how == "auto":
        how = "table" if math.comb(k, a) * math.comb(k, b) > PAIRS_PER_SPLIT * math.comb(k, t) * math.comb(t, a) else "residual"
    if how == "residual":
        return combine(keep, sums, step.d)
    return (combine_by_table if how == "table" else combine_packed)(keep, sums, step.d, k, t, a)


def _divided(out: DataFrame, d: int) -> DataFrame:
    # exact: every occurrence was produced d times
    if d == 1:
        return out
    kind = out.schema["cnt"].dataType
    by = F.expr(f"cnt div {d}") if kind.simpleString() == "bigint" else (F.col("cnt") / d).cast(kind)
    return out.withColumn("cnt", by)


def extend_edgewise(keep: DataFrame, cut: DataFrame, edges: DataFrame, d: int) -> DataFrame:
    """The step as it is defined: for each edge, kept counts of one end times cut counts of the other."""
    c = cut.select("it", F.col("v").alias("dst"), F.col("mask").alias("m2"), F.col("cnt").alias("n"))
    x = edges.select("src", "dst").join(c, "dst")
    j = x.join(keep.select("it", F.col("v").alias("src"), F.col("mask").alias("m1"), "cnt"), ["it", "src"]).where("(m1 & m2) = 0")
    out = j.groupBy("it", F.col("src").alias("v"), F.expr("m1 | m2").alias("mask")).agg(_total(F.col("cnt") * F.col("n"), keep, "cnt").alias("cnt"))
    return _divided(out, d)


def extend_sumfirst(keep: DataFrame, cut: DataFrame, edges: DataFrame, d: int) -> DataFrame:
    return combine(keep, neighbor_sums(cut, edges), d)


def split_table(spark: SparkSession, k: int, t: int, a: int) -> DataFrame:
    """(target, m1, m2): every way to split a set of t of k colours into a and t - a."""
    n = spark.range(1 << k).select(F.col("id").cast("int").alias("target")).where(F.expr("bit_count(target)") == t)
    # the sets that lie inside a target, from the bits outside it
    m = n.join(F.broadcast(spark.range(1 << k).select(F.col("id").cast("int").alias("m1")).where(F.expr("bit_count(m1)") == a)), F.expr("(m1 & ~target) = 0"))
    return m.select("target", "m1", F.expr("target & ~m1").alias("m2"))


# -- neighbour sums by mode ---------------------------------------------------------------------


def sums_bulk(cut: DataFrame, edges: DataFrame) -> DataFrame:
    return neighbor_sums(cut, edges)


def sums_local_remote(cut: DataFrame, edges: DataFrame, blocks: int) -> DataFrame:
    """Neighbours of the own block first, all others after; the parts add up."""
    own = block_of(F.col("src"), blocks) == block_of(F.col("dst"), blocks)
    parts = neighbor_sums(cut, edges.where(own)).unionByName(neighbor_sums(cut, edges.where(~own)))
    return parts.groupBy("it", "v", "mask").agg(_total(F.col("n"), cut, "cnt").alias("n"))


def sums_staged(cut: DataFrame, edges: DataFrame, blocks: int, group: int = 3, overlap: bool = True, name: str = "stage", spans: list | None = None) -> DataFrame:
    """Ring-staged exchange: step w brings counts from the blocks at ring distance in its group only.

    Each step's partial sums are written, so the data in flight at any time are one step's.  With
    ``overlap`` the next step's messages are selected while this step's sums run.  Edges with a ``slot``
    (`split_neighbor_lists`) are summed task by task.  The tables of the steps go once they are added up.
    ``spans`` gets (step, kind, start, finish) of every transfer and computation.
    """
    spark = cut.sparkSession
    per = max(1, (group - 1) // 2)
    steps = math.ceil((blocks - 1) / per)
    offset = ring_offset(F.col("src"), F.col("dst"), blocks)

    def message(w: int) -> tuple[DataFrame, DataFrame]:
        e = edges.where(offset == 0) if w == 0 else edges.where((offset > (w - 1) * per) & (offset <= w * per))
        wanted = e.select(F.col("dst").alias("v")).distinct()
        began = time.time()
        sent = written(cut.join(wanted, "v", "left_semi"), f"{name}-message")
        if spans is not None:
            spans.append((w, "transfer", began, time.time()))
        return e, sent

    def compute(e: DataFrame, counts: DataFrame) -> DataFrame:
        part = sums_split(counts, e) if "slot" in e.columns else neighbor_sums(counts, e)
        return written(part, f"{name}-sums")

    parts = []
    with ThreadPoolExecutor(1) as transfer:
        ahead = transfer.submit(message, 0)
        for w in range(steps + 1):
            now = ahead.result()
            if w < steps:
                ahead = transfer.submit(message, w + 1)
                if not overlap:
                    ahead.result()
            began = time.time()
            parts.append(compute(*now))
            if spans is not None:
                spans.append((w, "compute", began, time.time()))
            forget(now[1])
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    out = written(out.groupBy("it", "v", "mask").agg(_total(F.col("n"), cut, "cnt").alias("n")), f"{name}-total")
    for p in parts:
        forget(p)
    return out


def split_neighbor_lists(edges: DataFrame, s: int = 50, exact: bool = True) -> DataFrame:
    """(src, slot, dst): neighbour lists in slices of at most s (``exact``), or of about s by a hash without a sort."""
    if exact:
        from pyspark.sql import Window

        w = Window.partitionBy("src").orderBy(F.xxhash64("dst"), "dst")
        return edges.select("src", F.floor((F.row_number().over(w) - 1) / s).cast("int").alias("slot"), "dst")
    long = edges.groupBy("src").agg(F.ceil(F.count("*") / s).cast("int").alias("parts")).where("parts > 1")
    # written, so that the join can split the partition that gets a hub's whole list
    x = edges.join(written(long, "long-lists"), "src", "left")
    return x.select("src", F.coalesce(F.pmod(F.xxhash64("dst"), F.col("parts")).cast("int"), F.lit(0)).alias("slot"), "dst")


def sums_split(cut: DataFrame, tasks: DataFrame) -> DataFrame:
    """Two levels: sums of each slice, then of each vertex; a hub's slices are shared by many tasks."""
    c = cut.select("it", F.col("v").alias("dst"), "mask", "cnt")
    part = tasks.join(c, "dst").groupBy("it", "src", "slot", "mask").agg(_total(F.col("cnt"), cut, "cnt").alias("n"))
    return part.groupBy("it", F.col("src").alias("v"), "mask").agg(_total(F.col("n"), cut, "cnt").alias("n"))


# -- the whole program --------------------------------------------------------------------------


#: Defaults of the switch: vertices of a sub-template, the template's intensity, colour sets sent for a vertex.
SWITCH = {"size": 10, "intensity": 5.0, "cost": 100}


def is_large(step: SplitStep, template: TreeTemplate, switch: str = "size", threshold: float | None = None) -> bool:
    """Whether a sub-template is worth a staged exchange; small templates stay with one exchange by default."""
    measure = {"size": step.sizes[0], "intensity": intensity(template), "cost": math.comb(template.k, step.sizes[2])}[switch]
    return measure >= (SWITCH[switch] if threshold is None else threshold)


def rooted_counts(
    graph: EdgeGraph, template: TreeTemplate, coloring: DataFrame, mode: str = "bulk", blocks: int = 4, group: int = 3, s: int = 50, switch: str = "size", threshold: float | None = None,
    order: str = "heavy", share: bool = True, overlap: bool = True, root: int | None = None, count_type: str = "long", combine_by: str = "auto",
) -> DataFrame:
    """(it, v, mask, cnt) of the whole template at its root.

    The edges, the colouring and every sub-template that several steps read are written once: no step
    works out the graph or a shared table anew.
    """
    if mode not in MODES:
        raise ValueError(f"mode is one of {', '.join(MODES)}")
    plan = split_plan(template, root, order, share)
    k = template.k
    edges = stored(graph).edges if len(plan.steps) > 1 else graph.edges
    leaf = init_counts(written(coloring, "colors") if len(plan.steps) > 1 else coloring, count_type)
    table: dict[Shape, DataFrame] = {(): leaf}
    tasks = split_neighbor_lists(edges, s, exact=False) if mode == "adaptive_split" else None
    if tasks is not None and len(plan.steps) > 1:
        tasks = written(tasks, "tasks")
    sums: dict[Shape, DataFrame] = {}
    for n, step in enumerate(plan.steps):
        keep, cut = table[step.keep], table[step.cut]
        later = plan.steps[n + 1 :]
        if mode == "edgewise":
            out = extend_edgewise(keep, cut, edges, step.d)
        else:
            if step.cut not in sums:
                if mode == "staged" or (mode.startswith("adaptive") and is_large(step, template, switch, threshold)):
                    x = sums_staged(cut, edges if tasks is None else tasks, blocks, group, overlap)
                elif mode == "adaptive_split":
                    x = sums_split(cut, tasks)
                elif mode == "local_remote":
                    x = sums_local_remote(cut, edges, blocks)
                elif mode == "static_slots":
                    x = sums_static(cut, edges, blocks)
                elif mode == "resident_bulk":
                    # all received counts are held, one row an edge, before anything is summed
                    c = cut.select("it", F.col("v").alias("dst"), "mask", "cnt")
                    held = edges.join(c, "dst").persist()
                    x = written(held.groupBy("it", F.col("src").alias("v"), "mask").agg(_total(F.col("cnt"), cut, "cnt").alias("n")), "sums")
                    held.unpersist()
                else:
                    x = sums_bulk(cut, edges)
                sums[step.cut] = written(x, "sums") if mode != "resident_bulk" and any(y.cut == step.cut for y in later) else x
            out = combined(keep, sums[step.cut], step, k, combine_by)
        uses = sum((y.keep == step.whole) + (y.cut == step.whole) for y in later)
        if uses > 1 or (later and mode in ("disk_staged", "staged")):
            out = written(out, "counts")
        table[step.whole] = out
    return table[plan.top]


def sums_static(cut: DataFrame, edges: DataFrame, blocks: int) -> DataFrame:
    """The all-to-all with a fixed slot for each pair of blocks: as many partitions as blocks, whatever their sizes."""
    c = cut.select("it", F.col("v").alias("dst"), "mask", "cnt")
    sent = edges.select("src", "dst").join(c, "dst").withColumn("slot", block_of(F.col("src"), blocks)).repartition(blocks, "slot")
    return sent.groupBy("it", F.col("src").alias("v"), "mask").agg(_total(F.col("cnt"), cut, "cnt").alias("n"))


def replicated_counts(graph: EdgeGraph, template: TreeTemplate, iters: list[int], seed: int = 42, limit: int = 2_000_000) -> DataFrame:
    """(it, colorful): each colouring in one task with the whole graph; refuses graphs that would not fit one.

    Counts are doubles while all of them are below 2^53, where they are exact, and whole numbers of any size beyond.
    """
    edges = graph.edges
    n = edges.count()
    if n > limit:
        raise ValueError(f"{n} edges are too many to copy to every task")
    spark = edges.sparkSession
    if not n:
        return spark.createDataFrame([(i, 0) for i in iters], "it int, colorful long")
    import numpy as np

    plan, k = split_plan(template), template.k
    pdf = edges.toPandas().sort_values("src")
    nodes, first = np.unique(pdf["src"].to_numpy(), return_index=True)
    data = spark.sparkContext.broadcast((nodes, first, np.searchsorted(nodes, pdf["dst"].to_numpy()).astype(np.int32)))

    def run(batches):
        import pandas as pd

        ids, starts, far = data.value

        def total(it: int, kind) -> int:
            """The count of a colouring; doubles raise an error where they may not be exact."""

            def checked(x):
                if kind is float and x.max() >= 2.0**53:
                    raise OverflowError
                return x

            acc = np.zeros(len(ids), np.int64)
            for c in coefficients(k, it, seed):
                acc = (acc * (ids % PRIME) + c) % PRIME
            color = acc % k
            table: dict = {(): {1 << c: (color == c).astype(kind) for c in range(k)}}
            sums: dict = {}
            for step in plan.steps:
                if step.cut not in sums:
                    sums[step.cut] = {m: checked(np.add.reduceat(x[far], starts)) for m, x in table[step.cut].items()}
                whole: dict = {}
                for m1, x in table[step.keep].items():
                    for m2, y in sums[step.cut].items():
                        if not m1 & m2:
                            whole[m1 | m2] = whole[m1 | m2] + x * y if m1 | m2 in whole else x * y
                table[step.whole] = {m: checked(x) // step.d for m, x in whole.items()}
            full = table[plan.top].get((1 << k) - 1)
            return 0 if full is None else sum(map(int, full)) // plan.root_orbit

        for batch in batches:
            out = []
            for it in batch["it"]:
                try:
                    out.append((it, total(int(it), float)))
                except OverflowError:
                    out.append((it, total(int(it), object)))
            yield pd.DataFrame(out, columns=["it", "colorful"])

    # dealt evenly, a few colourings a task
    tasks = min(len(iters), 4 * spark.sparkContext.defaultParallelism)
    its = spark.createDataFrame([(i,) for i in iters], "it int").repartition(tasks)
    return its.mapInPandas(run, "it int, colorful long")


def colorful_count(graph: EdgeGraph, template: TreeTemplate, iters: list[int], seed: int = 42, mode: str = "bulk", scheme: str = "poly", colors: int | None = None, count_type: str = "long", **how) -> DataFrame:
    """(it, colorful): occurrences whose vertices all differ in colour, for each colouring.

    ``colorful`` has the type that ``count_type`` names; ``auto`` picks the narrowest that cannot overflow.  ``exact``
    counts in 64 bits and again in decimals where that overflows; its results are long if all of them fit.  Decimals
    of the modes ``bulk`` and ``adaptive_split`` come from arrays of vertex blocks (`residues`), not from rows of counts.
    """
    if count_type == "exact":
        return exact_counts(graph, template, iters, seed, mode, scheme, colors, **how)
    spark = graph.edges.sparkSession
    every = spark.createDataFrame([(i,) for i in iters], "it int")
    if mode == "replicated":
        return replicated_counts(graph, template, iters, seed)
    if count_type == "auto":
        graph = stored(graph)
        count_type = count_type_for(graph, template.k)
    if count_type == "decimal" and mode in ("bulk", "adaptive_split") and scheme == "poly" and colors is None and not how and residues.serves(template):
        totals = residues.colorful_totals(graph, template, iters, lambda it: coefficients(template.k, it, seed))
        return spark.createDataFrame([(i, Decimal(n)) for i, n in zip(iters, totals)], "it int, colorful decimal(38,0)")
    coloring = assign_colors(graph.nodes(), template.k, iters, seed, scheme, colors)
    counts = rooted_counts(graph, template, coloring, mode, count_type=count_type, **how)
    orbit = split_plan(template, how.get("root"), how.get("order", "heavy")).root_orbit
    kind = COUNT_TYPES[count_type]
    total = counts.where(F.expr(f"bit_count(mask) = {template.k}")).groupBy("it").agg(F.sum("cnt").cast(kind).alias("c"))
    whole = F.coalesce("c", F.lit(0).cast(kind))
    whole = whole if orbit == 1 else F.expr(f"coalesce(c, 0) div {orbit}") if count_type == "long" else whole / orbit
    return every.join(total, "it", "left").select("it", whole.cast(kind).alias("colorful"))


def expected_count(graph: EdgeGraph, template: TreeTemplate) -> float:
    """Colourful occurrences that a colouring finds on average, at most: images of the template, in doubles and without colours."""
    plan = split_plan(template)
    edges = graph.edges
    table: dict[Shape, DataFrame] = {(): graph.nodes().select("v", F.lit(1.0).alias("x"))}
    for step in plan.steps:
        s = edges.join(table[step.cut].select(F.col("v").alias("dst"), "x"), "dst").groupBy(F.col("src").alias("v")).agg(F.sum("x").alias("y"))
        table[step.whole] = written(table[step.keep].join(s, "v").select("v", (F.col("x") * F.col("y") / step.d).alias("x")), "images")
    out = table[plan.top].agg(F.sum("x")).first()[0] or 0.0
    for x in table.values():
        forget(x)
    return out / float(scale_up(template.k))


def exact_counts(graph: EdgeGraph, template: TreeTemplate, iters: list[int], seed: int = 42, *args, **how) -> DataFrame:
    """`colorful_count` with exact results of any size up to 32 digits; rows of counts are not tried for the widest templates."""
    from pyspark.errors import ArithmeticException

    graph = stored(graph)
    if math.comb(template.k, template.k // 2) <= ROWS_SETS and expected_count(graph, template) < LONG_LIMIT:
        try:
            return written(colorful_count(graph, template, iters, seed, *args, count_type="long", **how), "counts")
        except ArithmeticException:
            pass
    return narrowed(written(colorful_count(graph, template, iters, seed, *args, count_type="decimal", **how), "counts"), "colorful")


def per_vertex_counts(graph: EdgeGraph, template: TreeTemplate, iters: list[int], seed: int = 42, mode: str = "bulk", **how) -> DataFrame:
    """(it, v, cnt): colourful occurrences with the template's root at each vertex."""
    coloring = assign_colors(graph.nodes(), template.k, iters, seed)
    counts = rooted_counts(graph, template, coloring, mode, **how)
    return counts.groupBy("it", "v").agg(_total(F.col("cnt"), counts, "cnt").alias("cnt"))


# -- estimates ----------------------------------------------------------------------------------


def unbias(colorful: DataFrame, k: int, colors: int | None = None) -> DataFrame:
    """Adds ``estimate``: an unbiased estimate of the number of occurrences."""
    return colorful.withColumn("estimate", F.col("colorful").cast("double") * F.lit(float(scale_up(k, colors))))


def group_means(estimates: DataFrame, t: int) -> DataFrame:
    return estimates.groupBy(F.pmod("it", F.lit(t)).alias("grp")).agg(F.avg("estimate").alias("z"))


def median_of_means(estimates: DataFrame, t: int) -> DataFrame:
    """(estimate, lo, hi): median of t group means, and their range."""
    return group_means(estimates, t).agg(F.expr("percentile(z, 0.5)").alias("estimate"), F.min("z").alias("lo"), F.max("z").alias("hi"))


def estimate_tree_count(graph: EdgeGraph, template: TreeTemplate, eps: float = 0.5, delta: float = 0.1, seed: int = 42, mode: str = "auto", const: float = 1.0, cap: int | None = None, batch: int = 16, **how) -> DataFrame:
    """(estimate, lo, hi, n_iter, t): within eps of the count with probability 1 - delta (without a cap on the colourings).

    ``auto`` deals the colourings to tasks that hold the whole graph while it has ``COPY_EDGES`` edges at most, and
    joins beyond, as many colourings at a time as ``batch`` or ``BATCH_ROWS`` colours of vertices allow.
    """
    n, t = n_colorings(template.k, eps, delta, const, cap)
    graph, parts = stored(graph), []
    if mode == "auto":
        mode = "bulk" if how or graph.edges.count() > COPY_EDGES else "replicated"
        batch = n if mode == "replicated" else max(batch, min(64, BATCH_ROWS // max(1, graph.nodes().count())))
    for lo in range(1, n + 1, batch):
        x = unbias(colorful_count(graph, template, list(range(lo, min(lo + batch, n + 1))), seed, mode, **how), template.k)
        parts.append(written(x, "estimates") if n > batch else x)
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return median_of_means(out, t).withColumns({"n_iter": F.lit(n), "t": F.lit(t)})


def estimator_spread(estimates: DataFrame) -> DataFrame:
    return estimates.agg(F.count("*").alias("n"), F.avg("estimate").alias("mean"), F.stddev_samp("estimate").alias("sd"), (F.stddev_samp("estimate") / F.sqrt(F.count("*"))).alias("se"))


def tree_exists(graph: EdgeGraph, template: TreeTemplate, fail: float = 0.01, seed: int = 42, batch: int = 8) -> bool:
    """Whether the template occurs; never a false yes, a false no with probability ``fail`` at most."""
    n = max(1, math.ceil(math.log(1 / fail) * scale_up(template.k)))
    graph = stored(graph)
    # one colouring first and twice as many in each batch after it: a frequent template shows in the first ones
    lo, size = 1, 1
    while lo <= n:
        its = list(range(lo, min(lo + size, n + 1)))
        lo, size = lo + size, min(2 * size, batch)
        # sums of doubles that are not negative neither vanish nor overflow here; ids may be hashes
        counts = rooted_counts(graph, template, assign_colors(graph.nodes(), template.k, its, seed, "xxhash"), count_type="double")
        if counts.where(F.expr(f"bit_count(mask) = {template.k}")).limit(1).count():
            return True
    return False


def tree_frequencies(graph: EdgeGraph, templates: dict[str, TreeTemplate], eps: float = 0.5, delta: float = 0.1, seed: int = 42) -> DataFrame:
    """(template, estimate, share): all estimates within eps with probability 1 - delta, and each one's share of them all."""
    from pyspark.sql import Window

    graph, out = stored(graph), None
    for name, t in templates.items():
        x = estimate_tree_count(graph, t, eps, delta / len(templates), seed).select(F.lit(name).alias("template"), "estimate")
        out = x if out is None else out.unionByName(x)
    total = F.sum("estimate").over(Window.partitionBy())  # a row a template
    return out.withColumn("share", F.when(total > 0, F.col("estimate") / total).otherwise(F.lit(0.0)))


def frequent_trees(graph: EdgeGraph, k: int, least: float, eps: float = 0.5, delta: float = 0.1, seed: int = 42) -> DataFrame:
    """The trees with k vertices whose estimated count is at least ``least``."""
    from ..plans.templates import all_free_trees

    named = {" ".join(map(str, t.parents)): t for t in all_free_trees(k)}
    return tree_frequencies(graph, named, eps, delta, seed).where(F.col("estimate") >= least)


def sample_embeddings(graph: EdgeGraph, template: TreeTemplate, n: int, seed: int = 42, it: int = 1) -> DataFrame:
    """(v0.., v_{k-1}): n colourful occurrences, or all where there are fewer, down the tables of the dynamic program.

    Vertices are numbered as the walk meets them (`walk_parents` gives the template edges).  Every partial
    occurrence has a non-zero count, so each can be completed; the n of least hash go on after each step.
    """
    from pyspark.sql import Window

    spark = graph.edges.sparkSession
    plan = split_plan(template)
    graph = stored(graph)
    edges, nodes = graph.edges, graph.nodes()
    leaf = init_counts(assign_colors(nodes, template.k, [it], seed))
    table: dict[Shape, DataFrame] = {(): written(leaf.select("v", "mask", "cnt"), "counts")}
    for step in plan.steps:
        keep, cut = (table[x].withColumn("it", F.lit(it)) for x in (step.keep, step.cut))
        table[step.whole] = written(combined(keep, neighbor_sums(cut, edges), step, template.k).select("v", "mask", "cnt"), "counts")
    by_whole = {x.whole: x for x in plan.steps}
    part = table[plan.top].where("cnt > 0").select(F.col("v").alias("x0"), F.col("mask").alias("m0"))
    todo, placed, number = [(plan.top, 0)], [], 1
    while todo:
        shape, at = todo.pop()
        if shape == ():
            placed.append(at)
            continue
        step = by_whole[shape]
        old = part.columns
        part = part.join(table[step.keep].where("cnt > 0").select(F.col("v").alias(f"x{at}"), F.col("mask").alias("part")), f"x{at}").where(f"(part & ~m{at}) = 0")
        part = part.withColumn("rest", F.expr(f"m{at} & ~part")).join(edges.select(F.col("src").alias(f"x{at}"), F.col("dst").alias("u")), f"x{at}")
        part = part.join(table[step.cut].where("cnt > 0").select(F.col("v").alias("u"), F.col("mask").alias("rest")), ["u", "rest"])
        part = part.select(*[c for c in old if c != f"m{at}"], F.col("part").alias(f"m{at}"), F.col("u").alias(f"x{number}"), F.col("rest").alias(f"m{number}"))
        xs = [c for c in part.columns if c[0] == "x"]
        part = written(part.orderBy(F.xxhash64(*sorted(xs), F.lit(seed)), *sorted(part.columns)).limit(n), "embeddings")  # the n of least hash
        todo += [(step.cut, number), (step.keep, at)]
        number += 1
    return part.select(*[F.col(f"x{at}").alias(f"v{i}") for i, at in enumerate(placed)]).distinct()


def walk_parents(template: TreeTemplate) -> list[int]:
    """Parent of each column of `sample_embeddings`; -1 for the first."""
    plan = split_plan(template)
    by_whole = {x.whole: x for x in plan.steps}
    todo, placed, parent, number = [(plan.top, 0)], [], {0: -1}, 1
    while todo:
        shape, at = todo.pop()
        if shape == ():
            placed.append(at)
            continue
        step = by_whole[shape]
        parent[number] = at
        todo += [(step.cut, number), (step.keep, at)]
        number += 1
    place = {at: i for i, at in enumerate(placed)}
    return [place.get(parent[at], -1) for at in placed]
