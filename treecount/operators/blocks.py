"""Common neighbours without a list of all pairs of neighbours: each task holds the neighbour lists of two vertex blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .exchange import forget, release, written

#: List entries that one task holds at most, on average; fewer blocks mean less data sent.
ENTRIES = 24_000_000
#: Blocks of a graph that would fit one task but takes a while there.
SPREAD = 6


def packed_lists(edges: DataFrame, up: bool) -> DataFrame:
    """(v, deg, n, data): each vertex's sorted neighbours as gaps, in as few bytes as its largest gap takes.

    With ``up`` the list keeps the neighbours beyond the vertex only; ``deg`` counts all of them.
    """

    def pack(batches):
        import numpy as np
        import pyarrow as pa

        def rows(src, dst):
            first = np.flatnonzero(np.r_[True, src[1:] != src[:-1]]) if len(src) else np.empty(0, np.int64)
            deg = np.diff(np.r_[first, len(src)])
            v = src[first]
            keep = dst > src if up else np.ones(len(src), bool)
            n = np.add.reduceat(keep, first, dtype=np.int64) if len(first) else deg
            dst = dst[keep]
            start = np.r_[0, np.cumsum(n)]
            gap = np.diff(dst, prepend=0)
            at = start[:-1][n > 0]
            gap[at] = dst[at] - (v[n > 0] if up else 0)
            data = []
            for lo, hi in zip(start[:-1].tolist(), start[1:].tolist()):
                g = gap[lo:hi]
                # ids below zero give a first gap below zero, which only the widest type keeps
                top = int(g.view(np.uint64).max()) if hi > lo else 0
                data.append(g.astype(np.uint8 if top < 1 << 8 else np.uint16 if top < 1 << 16 else np.uint32 if top < 1 << 32 else np.int64).tobytes())
            return pa.record_batch({"v": v, "deg": deg, "n": n, "data": pa.array(data, pa.binary())})

        held = []
        for b in batches:
            if not b.num_rows:
                continue
            held.append((b.column("src").to_numpy(), b.column("dst").to_numpy()))
            # the last vertex of a batch may go on in the next
            if sum(len(x) for x, _ in held) < 200_000 or held[0][0][0] == held[-1][0][-1]:
                continue
            src, dst = (np.concatenate(x) for x in zip(*held))
            cut = int(np.searchsorted(src, src[-1]))
            yield rows(src[:cut], dst[:cut])
            held = [(src[cut:], dst[cut:])]
        if held:
            yield rows(*(np.concatenate(x) for x in zip(*held)))

    dealt = edges.select("src", "dst").where("src is not null").repartition("src").sortWithinPartitions("src", "dst")
    return dealt.mapInArrow(pack, "v long, deg long, n long, data binary")


def written_lists(edges: DataFrame, up: bool, last: bool = False) -> DataFrame:
    """`packed_lists` as a table; the edges' shuffle files go before, and so do edges written here or read for the ``last`` time."""
    own = getattr(edges, "_store_path", None) is None
    table = written(edges, "edges") if own else edges
    release(edges.sparkSession)
    lists = written(packed_lists(table, up), "lists")
    if own or last:
        forget(table)
    release(edges.sparkSession)
    return lists


def over_pairs(lists: DataFrame, work, schema: str, names: tuple[str, ...], up: bool) -> DataFrame:
    """The columns that ``work`` makes of the lists of each pair of blocks, a block with itself among them.

    ``work`` gets the pair, and the blocks, degrees, lists and ids of the vertices of both, by ascending vertex.
    """
    spark = lists.sparkSession
    total = lists.agg(F.sum("n")).first()[0] or 0
    blocks = max(1, -(-2 * total // ENTRIES), min(SPREAD, -(-total // 500_000)))
    own = lists.withColumn("i", F.pmod(F.xxhash64("v"), F.lit(blocks)).cast("int")).withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    sent = own.select((F.least("i", "j") * blocks + F.greatest("i", "j")).alias("pair"), "i", "v", "deg", "n", "data")
    sent = sent.repartition(4 * blocks * (blocks + 1), "pair")  # several times the pairs, so that few share a partition

    # inside, as a task may run where this package is not installed
    def compact(values):
        """Dense numbers of whole numbers in their order, and how many there are."""
        import numpy as np

        if not len(values):
            return values, 0
        lo, span = values.min(), int(values.max()) - int(values.min())
        if span < 8 * len(values) + 1024:
            seen = np.zeros(span + 1, bool)
            seen[values - lo] = True
            number = np.cumsum(seen, dtype=np.int32) - np.int32(1)
            return number[values - lo], int(number[-1]) + 1
        ids, place = np.unique(values, return_inverse=True)
        return place.astype(np.int32), len(ids)

    def unpacked(table):
        """(order of the rows by vertex, vertices, lengths, entries, numbers in all): vertices and entries as dense numbers."""
        import numpy as np
        import pyarrow as pa

        v, n = table.column("v").to_numpy(), table.column("n").to_numpy()
        order = np.argsort(v)
        table = table.take(pa.array(order))
        v, n = v[order], n[order]
        start = np.r_[0, np.cumsum(n)]
        gap = np.empty(start[-1], np.int64)
        size = np.fromiter((len(x) for x in table.column("data").to_numpy(zero_copy_only=False)), np.int64, len(v)) if len(v) else n
        width = size // np.maximum(n, 1)
        for w, kind in ((1, np.uint8), (2, np.uint16), (4, np.uint32), (8, np.int64)):
            some = width == w
            if some.any():
                part = b"".join(table.column("data").filter(pa.array(some)).to_pylist())
                gap[np.repeat(some, n)] = np.frombuffer(part, kind)
        # sums along each list: running sums less what came before the list, from the vertex on
        total = np.cumsum(gap)
        before = np.r_[0, total][start[:-1]]
        entries = total - np.repeat(before - (v if up else 0), n)
        number, size = compact(np.concatenate([v, entries]))
        return order, number[: len(v)].astype(np.int64), n, number[len(v) :], size

    def run(table):
        import pyarrow as pa

        p, q = divmod(table.column("pair")[0].as_py(), blocks)
        order, v, n, entries, size = unpacked(table)
        block, deg, ids = (table.column(c).to_numpy()[order] for c in ("i", "deg", "v"))
        return pa.table(dict(zip(names, work(p, q, block, deg, v, n, entries, size, ids))))

    return sent.groupBy("pair").applyInArrow(run, schema)


def open_ends_and_triangles(edges: DataFrame) -> DataFrame:
    """(ends, triangles): sum over the edges of (deg - 1) * (deg - 1), and the number of triangles, each at the edge of its two lower vertices.

    An edge looks the shorter of its two lists up in the longer, which bounds the work of hubs.
    """

    def work(p, q, block, deg, v, n, entries, size, ids):
        import numpy as np

        place = np.full(size, -1, np.int32)
        place[v] = np.arange(len(v), dtype=np.int32)
        start = np.r_[0, np.cumsum(n)]
        one, two = np.repeat(np.arange(len(v), dtype=np.int32), n), place[entries]
        here = two >= 0
        one, two = one[here], two[here]
        if p != q:
            across = block[one] != block[two]
            one, two = one[across], two[across]
        x = (deg[one] - 1) * (deg[two] - 1)
        ends = (int((x >> 32).sum()) << 32) + int((x & 0xFFFFFFFF).sum())
        less = n[one] <= n[two]
        short, long = np.where(less, one, two), np.where(less, two, one)
        some = n[short] > 0
        short, long = short[some], long[some]
        order = np.argsort(long, kind="stable")
        short, long = short[order], long[order]
        done = np.r_[0, np.cumsum(n[short])]
        # edges of some consecutive longer lists at a time: their marks fit a table that stays small
        head = np.flatnonzero(np.r_[True, long[1:] != long[:-1]]) if len(long) else np.empty(0, np.int64)
        tail = np.r_[head[1:], len(long)] if len(long) else head
        rows = int(max(1, min(256, 64_000_000 // max(size, 1))))
        mark = np.zeros(rows * size, bool)
        found, g, by = 0, 0, done[tail]
        while g < len(head):
            h = min(int(np.searchsorted(by, done[head[g]] + 300_000)) + 1, g + rows, len(head))
            which = long[head[g:h]]
            m = n[which]
            row = np.repeat(np.arange(h - g) * size, m)
            at = row + entries[np.repeat(start[which] - np.r_[0, np.cumsum(m)[:-1]], m) + np.arange(m.sum())]
            mark[at] = True
            # a longer list of very many edges in parts
            lo, hi = int(head[g]), int(tail[h - 1])
            base = np.repeat(np.arange(h - g) * size, tail[g:h] - head[g:h])
            while lo < hi:
                to = max(lo + 1, min(hi, int(np.searchsorted(done, done[lo] + 1_000_000, "right")) - 1))
                s = short[lo:to]
                k = n[s]
                asked = entries[np.repeat(start[s] - (done[lo:to] - done[lo]), k) + np.arange(done[to] - done[lo])]
                found += int(np.count_nonzero(mark[np.repeat(base[lo - int(head[g]) : to - int(head[g])], k) + asked]))
                lo = to
            mark[at] = False
            g = h
        return [str(ends)], [found]

    lists = written_lists(edges, True)
    out = written(over_pairs(lists, work, "ends string, triangles long", ("ends", "triangles"), True), "found")
    forget(lists)
    return out.agg(F.coalesce(F.sum(F.col("ends").cast("decimal(28,0)")), F.lit(0)).cast("decimal(38,0)").alias("ends"), F.coalesce(F.sum("triangles"), F.lit(0)).alias("triangles"))


def ranked(graph) -> DataFrame:
    """Edges with numbers that ascend by (degree, id) in place of ids; the numbers have gaps."""
    d = graph.edges.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg"))
    r = written(d.orderBy("deg", "v").select("v", F.monotonically_increasing_id().alias("r")), "ranks")
    e = graph.edges.join(r.select(F.col("v").alias("src"), F.col("r").alias("rs")), "src").join(r.select(F.col("v").alias("dst"), F.col("r").alias("rd")), "dst")
    return e.select(F.col("rs").alias("src"), F.col("rd").alias("dst"))


def four_cycles_of(ranked_edges: DataFrame, last: bool = False, triangles: bool = False) -> DataFrame:
    """(cycles): cycles of four, each at its highest vertex: two steps by way of a lower vertex, counted by their lower ends.

    With ``triangles`` also ``around``: over all triangles, four times their degrees less 18.  A triangle is two steps
    to a lower end that is a neighbour, by way of either of its lower vertices.
    """

    def work(p, q, block, deg, v, n, entries, size, ids):
        import numpy as np

        owner = np.repeat(np.arange(len(v)), n)
        start = np.r_[0, np.cumsum(n)]
        cycles, around = 0, 0
        row = np.full(size, -1, np.int64)
        row[v] = np.arange(len(v))
        for near, far in {(p, q), (q, p)}:
            # from each vertex to its neighbours in the far block, by their places there
            ends = np.flatnonzero(block == far)
            place = np.full(len(v), -1, np.int64)
            place[ends] = np.arange(len(ends))
            there = place[owner] >= 0
            m = entries[there]
            to = place[owner[there]][np.argsort(m, kind="stable")]
            first = np.r_[0, np.cumsum(np.bincount(m, minlength=size))]
            below = np.searchsorted(v[ends], v)
            for a in np.flatnonzero(block == near).tolist():
                way = entries[start[a] : start[a + 1]]
                way = way[: np.searchsorted(way, v[a])]
                lo, hi = first[way].tolist(), first[way + 1].tolist()
                parts = [to[x:y] for x, y in zip(lo, hi) if y > x]
                if not parts or len(way) < 2:
                    continue
                b = np.concatenate(parts)
                if triangles:
                    # lower neighbours in the far block, by their places there
                    r = row[way]
                    r = r[r >= 0]
                    r = r[place[r] >= 0]
                    t = place[r]
                if len(b) * 4 > len(ends):
                    c = np.bincount(b, minlength=len(ends))[: below[a]]
                    m = c[t] if triangles else None
                else:
                    b = np.sort(b[b < below[a]])
                    c = np.diff(np.flatnonzero(np.r_[True, b[1:] != b[:-1], True])) if len(b) else b
                    m = np.searchsorted(b, t, "right") - np.searchsorted(b, t) if triangles else None
                cycles += int(c @ (c - 1)) // 2
                if triangles:
                    around += int(m @ (2 * deg[a] + 4 * deg[r] - 9))
        return ([cycles], [str(around)]) if triangles else ([cycles],)

    lists = written_lists(ranked_edges, False, last)
    schema, names = ("cycles long, around string", ("cycles", "around")) if triangles else ("cycles long", ("cycles",))
    out = written(over_pairs(lists, work, schema, names, False), "found")
    forget(lists)
    cycles = F.coalesce(F.sum("cycles"), F.lit(0)).alias("cycles")
    around = F.coalesce(F.sum(F.col("around").cast("decimal(28,0)")), F.lit(0)).cast("decimal(38,0)").alias("around") if triangles else None
    return out.agg(cycles, around) if triangles else out.agg(cycles)


def two_hop_counts(edges: DataFrame) -> DataFrame:
    """(src, n): distinct vertices two steps away, other than the vertex itself, counted block by block and added up."""

    def work(p, q, block, deg, v, n, entries, size, ids):
        import numpy as np

        owner = np.repeat(np.arange(len(v)), n)
        start = np.r_[0, np.cumsum(n)]
        src, far_ones = [], []
        for near, far in {(p, q), (q, p)}:
            ends = np.flatnonzero(block == far)
            place = np.full(len(v), -1, np.int64)
            place[ends] = np.arange(len(ends))
            there = place[owner] >= 0
            m = entries[there]
            to = place[owner[there]][np.argsort(m, kind="stable")]
            first = np.r_[0, np.cumsum(np.bincount(m, minlength=size))]
            mark = np.zeros(len(ends), bool)
            for a in np.flatnonzero(block == near).tolist():
                way = entries[start[a] : start[a + 1]]
                lo, hi = first[way].tolist(), first[way + 1].tolist()
                if sum(hi) - sum(lo) > len(ends):
                    for x, y in zip(lo, hi):
                        mark[to[x:y]] = True
                    c = int(np.count_nonzero(mark))
                    mark[:] = False
                else:
                    parts = [to[x:y] for x, y in zip(lo, hi) if y > x]
                    c = 0
                    if parts:
                        b = np.sort(np.concatenate(parts))
                        c = 1 + int(np.count_nonzero(b[1:] != b[:-1]))
                # each neighbour leads back
                c -= near == far
                if c:
                    src.append(int(ids[a]))
                    far_ones.append(c)
        import pyarrow as pa

        return pa.array(src, pa.int64()), pa.array(far_ones, pa.int64())

    lists = written_lists(edges, False)
    out = written(over_pairs(lists, work, "src long, n long", ("src", "n"), False), "found")
    forget(lists)
    return out.groupBy("src").agg(F.sum("n").alias("n"))
