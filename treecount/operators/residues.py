"""Exact counts of any size in whole numbers: the dynamic program over vertex blocks, modulo primes.

A table holds, for each block of vertices and each colour, the counts of the vertices of that colour for the colour
sets that it is in, modulo one prime; all other counts are zero.  A task has the vertices of one colour in one block.  It
adds up the counts of their neighbours for the sets without its colour, so every neighbour list is cut by the colours and
blocks of its far ends and its parts are added, and combines them with the kept part's table.  Only the count of the whole
leaves the tasks; the primes, one after the other, give it exactly.  As many are taken as the images of the template,
which bound the count, ask for.
"""

from __future__ import annotations

import itertools
import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.templates import Shape, SplitPlan, TreeTemplate, size, split_plan
from ..sources.graphs import EdgeGraph
from .exchange import forget, fresh_path, release, written

#: Largest primes below 2^30: SPLITS products of two residues add up in 64 bits.
PRIMES = (1073741789, 1073741783, 1073741741, 1073741723, 1073741719, 1073741717, 1073741689, 1073741671, 1073741663, 1073741651, 1073741621, 1073741567)
SPLITS = 16
#: Numbers of one task's neighbour sums, and edges of one block, on average.
NUMBERS = 16_000_000
EDGES = 4_000_000
#: Neighbours of one colour and block beyond which a vertex gets their sum, and their counts are not read one by one.
LONG = 16
#: Numbers that a task works on at a time: few enough for a core's cache.
PART = 131_072
#: Colour sets that a table may have; beyond, the tables of rows are used.
SETS = 6435


def serves(template: TreeTemplate) -> bool:
    return template.k > 1 and math.comb(template.k, template.k // 2) <= SETS


def _delete(spark: SparkSession, path: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def _files(root: str):
    """(read, write) of lists of numpy arrays below the shared folder; nested, as a task may run where this package is not installed."""

    def at(name: str):
        from pyarrow import fs

        uri = "file://" + root[5:] if root.startswith("file:") and "://" not in root else root
        if "://" not in uri:
            uri = "file://" + uri
        system, path = fs.FileSystem.from_uri(uri)
        return system, f"{path}/{name}"

    def write(name: str, arrays) -> None:
        import pyarrow as pa

        system, path = at(name)
        system.create_dir(path.rsplit("/", 1)[0], recursive=True)
        with system.open_output_stream(path) as out:
            schema = pa.schema([("data", pa.large_binary())])
            with pa.ipc.new_file(out, schema, options=pa.ipc.IpcWriteOptions(compression="lz4")) as w:
                for x in arrays:
                    w.write_batch(pa.record_batch([pa.array([x.tobytes()], pa.large_binary())], schema=schema))

    def read(name: str, kind, only=None):
        """The arrays one after the other, or one of them; none where there is no such file."""
        import numpy as np
        import pyarrow as pa

        system, path = at(name)
        if system.get_file_info(path).type.name == "NotFound":
            return
        with system.open_input_file(path) as f:
            r = pa.ipc.open_file(f)
            for i in range(r.num_record_batches) if only is None else [only]:
                yield np.frombuffer(r.get_batch(i).column(0)[0].as_buffer(), kind)

    return read, write


def colorful_totals(graph: EdgeGraph, template: TreeTemplate, its: list[int], coefficients) -> list[int]:
    """The number of colourful occurrences for each colouring; ``coefficients`` gives those of a colouring's polynomial."""
    spark, plan = graph.edges.sparkSession, split_plan(template)
    own = getattr(graph.edges, "_store_path", None) is None
    edges = written(graph.edges, "edges") if own else graph.edges
    release(spark)
    n = edges.count()
    if not n:
        return [0] * len(its)
    root = fresh_path(spark, "residues")
    try:
        vertices = edges.agg(F.approx_count_distinct("src")).first()[0]
        # colour sets of a vertex in its sums, or in a table: those without or with its own colour
        widest = max(math.comb(template.k - 1, size(x) - i) for s in plan.steps for x, i in ((s.cut, 0), (s.cut, 1), (s.whole, 1)))
        blocks = max(1, -(-n // EDGES), -(-vertices * widest // (NUMBERS * template.k)))
        _numbered(edges, root, blocks)
        if own:
            forget(edges)
        release(spark)
        tables = _Tables(spark, plan, template.k, root, blocks)
        bound, count, product = tables.images(), 0, 1
        while product <= 1.01 * bound + 1:
            product *= PRIMES[count]
            count += 1
        out = []
        for it in its:
            x, modulus = 0, 1
            tables.colored(coefficients(it))
            for p in PRIMES[:count]:
                r = tables.total(p)
                x += modulus * ((r - x) * pow(modulus, -1, p) % p)
                modulus *= p
            out.append(x // plan.root_orbit)
        return out
    finally:
        _delete(spark, root)


def _numbered(edges: DataFrame, root: str, blocks: int) -> None:
    """Files of each block's vertices in ascending order, and of each pair of blocks its edges by their places there."""
    read, write = _files(root)
    block = lambda c: F.pmod(F.xxhash64(c), F.lit(blocks)).cast("int")

    def vertices(table):
        import numpy as np
        import pyarrow as pa

        p = table.column("p")[0].as_py()
        write(f"v/{p}", [np.sort(table.column("src").to_numpy())])
        return pa.table({"n": pa.array([table.num_rows], pa.int64())})

    def pair(table):
        import numpy as np
        import pyarrow as pa

        p, q = divmod(table.column("pq")[0].as_py(), blocks)
        (a,), (b,) = read(f"v/{p}", np.int64), read(f"v/{q}", np.int64)
        src, dst = np.searchsorted(a, table.column("src").to_numpy()), np.searchsorted(b, table.column("dst").to_numpy())
        order = np.argsort(src * len(b) + dst)
        src, dst = src[order].astype(np.int32), dst[order].astype(np.int32)
        starts = np.flatnonzero(np.r_[True, src[1:] != src[:-1]])
        write(f"e/{p}-{q}", [src[starts], starts.astype(np.int64), dst])
        return pa.table({"n": pa.array([table.num_rows], pa.int64())})

    edges.select("src").distinct().withColumn("p", block("src")).groupBy("p").applyInArrow(vertices, "n long").agg(F.sum("n")).collect()
    release(edges.sparkSession)
    dealt = edges.select((block("src") * blocks + block("dst")).alias("pq"), "src", "dst")
    dealt.groupBy("pq").applyInArrow(pair, "n long").agg(F.sum("n")).collect()


class _Tables:
    """The program's tables in files, and the jobs that make them; a table goes after its last use."""

    def __init__(self, spark: SparkSession, plan: SplitPlan, k: int, root: str, blocks: int):
        self.spark, self.plan, self.k, self.root, self.blocks = spark, plan, k, root, blocks
        self.name: dict[Shape, str] = {s.whole: f"t{i}" for i, s in enumerate(plan.steps)}

    def _run(self, work, parts: int = 1) -> list:
        """What ``work`` gives for every block, or for each of a block's parts, each in a task of its own."""

        def run(batches):
            import pyarrow as pa

            for b in batches:
                for p in b.column("id").to_pylist():
                    yield pa.record_batch([pa.array([str(work(p))])], names=["x"])

        n = self.blocks * parts
        return [r["x"] for r in self.spark.range(0, n, 1, n).mapInArrow(run, "x string").collect()]

    def _steps(self, job, parts: int = 1) -> list:
        """The results of the last of the steps, whose tables go once nothing reads them."""
        steps, out = self.plan.steps, []
        for i, step in enumerate(steps):
            out = self._run(job(step, step.whole == self.plan.top), parts)
            later = {x for s in steps[i + 1 :] for x in (s.keep, s.cut)}
            for x in {step.keep, step.cut} - later - {()}:
                _delete(self.spark, f"{self.root}/{self.name[x]}")
        return out

    def images(self) -> float:
        """Images of the template in doubles, without colours: no colouring has more occurrences."""
        read, write = _files(self.root)
        blocks, name = self.blocks, self.name

        def job(step, last):
            keep, cut, whole, d = name.get(step.keep), name.get(step.cut), name[step.whole], step.d

            def work(p):
                import numpy as np

                (ids,) = read(f"v/{p}", np.int64)
                sums = np.zeros(len(ids))
                for q in range(blocks):
                    e = list(read(f"e/{p}-{q}", np.int32))
                    if not e:
                        continue
                    rows, starts, far = e[0], e[1].view(np.int64), e[2]
                    if cut is None:
                        sums[rows] += np.diff(np.r_[starts, len(far)])
                    else:
                        (x,) = read(f"{cut}/{q}", np.float64)
                        sums[rows] += np.add.reduceat(x[far], starts)
                if keep is not None:
                    sums *= next(read(f"{keep}/{p}", np.float64))
                sums /= d
                if not last:
                    write(f"{whole}/{p}", [sums])
                return repr(float(sums.sum()))

            return work

        return sum(map(float, self._steps(job)))

    def colored(self, polynomial: list[int]) -> None:
        """Files of each block's edges for each pair of colours and each block with the far ends, by places within the colours."""
        read, write = _files(self.root)
        k, blocks = self.k, self.blocks

        def work(p):
            import numpy as np

            def places(q):
                """(colour, place among the block's vertices of that colour, how many of each colour) of a block's vertices."""
                (ids,) = read(f"v/{q}", np.int64)
                acc = np.zeros(len(ids), np.int64)
                for c in polynomial:
                    acc = (acc * (ids % 2147483647) + c) % 2147483647
                color = acc % k
                n = np.bincount(color, minlength=k)
                place = np.empty(len(ids), np.int64)
                place[np.argsort(color, kind="stable")] = np.arange(len(ids)) - np.repeat(np.cumsum(n) - n, n)
                return color, place, n

            color, place, n = places(p)
            write(f"c/{p}", [n])
            for q in range(blocks):
                near, far = [], []
                e = list(read(f"e/{p}-{q}", np.int32))
                if e:
                    c2, place2, _ = places(q)
                    rows, starts = e[0].astype(np.int64), e[1].view(np.int64)
                    rows = np.repeat(rows, np.diff(np.r_[starts, len(e[2])]))
                    # colours of both ends and place of the near one; place of the far one
                    near.append((color[rows] * k + c2[e[2]] << 32) + place[rows])
                    far.append(place2[e[2]])
                key = np.concatenate(near) if near else np.empty(0, np.int64)
                order = np.argsort(key, kind="stable")
                key, to = key[order], np.concatenate(far)[order].astype(np.int32) if near else np.empty(0, np.int32)
                cut = np.searchsorted(key, np.arange(k * k + 1) << 32)

                def parts():
                    for lo, hi in zip(cut[:-1], cut[1:]):
                        row = (key[lo:hi] & 0xFFFFFFFF).astype(np.int32)
                        first = np.flatnonzero(np.r_[True, row[1:] != row[:-1]][: len(row)]).astype(np.int32)
                        yield row[first]
                        yield first
                        yield to[lo:hi]

                write(f"c/{p}-{q}", parts())
            return 0

        self._run(work)

    def total(self, prime: int) -> int:
        """The sum of the whole template's colourful counts at all vertices, modulo a prime."""
        read, write = _files(self.root)
        k, blocks, name = self.k, self.blocks, self.name

        def job(step, last):
            (t, a, b), d = step.sizes, step.d
            keep, cut, whole, inverse = name.get(step.keep), name.get(step.cut), name[step.whole], pow(d, -1, prime)
            kept_later, cut_later = (any(getattr(s, x) == step.whole for s in self.plan.steps) for x in ("keep", "cut"))

            def work(task):
                import numpy as np

                p, c = divmod(task, k)

                def sets(n, size=k):
                    """Ascending sets of n colours of ``size``."""
                    m = np.arange(1 << size)
                    return m[sum(m >> i & 1 for i in range(size)) == n]

                def table(of, q, c, n):
                    """Counts of a block's vertices of colour c, a row each, for the colour sets of n with c."""
                    (x,) = read(f"{of}/{q}-{c}", np.uint32)
                    return x.reshape(-1, math.comb(k - 1, n - 1))

                def part(p, q, c, c2):
                    """(rows, the starts of their far ends, far ends, how many) of a pair of colours and blocks, the longest first."""
                    rows, first, far = (y for i in range(3) for y in read(f"c/{p}-{q}", np.int32, 3 * (c * k + c2) + i))
                    long = np.diff(np.r_[first, len(far)])
                    order = np.argsort(-long, kind="stable")
                    return rows[order], first[order], far, long[order]

                def added(y, x):
                    """y + x modulo the prime, for y below it."""
                    y = y + x
                    return np.minimum(y, y - np.uint32(prime))  # less than two primes, and below zero is large

                def put(sums, rows, columns, x):
                    for lo in range(0, len(rows), size := max(1, PART // len(columns))):
                        at = rows[lo : lo + size, None], columns
                        sums[at] = added(sums[at], x[lo : lo + size])

                def hand_out(x):
                    """Files of the sums for other tasks' vertices of many neighbours here, and of the counts that the others read."""
                    asked, size = np.zeros(len(x), bool), max(1, PART // x.shape[1])
                    m = sets(t)
                    m = m[m >> c & 1 == 1]
                    for q in range(blocks):
                        out = []
                        for c2 in range(k):
                            if c == c2:
                                out += [np.empty(0, np.int32), np.empty(0, np.uint32)]
                                continue
                            rows, first, far, long = part(q, p, c2, c)
                            hubs = int(np.count_nonzero(long > LONG))
                            total = np.zeros((hubs, x.shape[1]), np.uint64)
                            for i in range(hubs):
                                for lo in range(first[i], end := first[i] + long[i], size):
                                    total[i] += x[far[lo : min(lo + size, end)]].sum(0, dtype=np.uint64)
                            for j in range(int(long[hubs:].max(initial=0))):
                                asked[far[first[hubs : int(np.count_nonzero(long > j))] + j]] = True
                            out += [rows[:hubs], (total[:, m >> c2 & 1 == 0] % prime).astype(np.uint32)]
                        write(f"{whole}/s/{q}/{p}-{c}", out)
                    write(f"{whole}/a/{p}-{c}", [np.flatnonzero(asked), x[asked]])

                (sizes,) = read(f"c/{p}", np.int64)
                n = int(sizes[c])
                # neighbour sums for the sets without c; such sets, and sets with c, ascend as they do with c's bit taken out
                sums = np.zeros((n, math.comb(k - 1, b)), np.uint32)
                rank = np.full(1 << k, -1, np.int64)
                asked = sets(b)
                asked = asked[asked >> c & 1 == 0]
                rank[asked] = np.arange(len(asked))
                for q in range(blocks) if n else ():
                    for c2 in range(k):
                        if c == c2:
                            continue
                        rows, first, far, long = part(p, q, c, c2)
                        if not len(far):
                            continue
                        if cut is None:
                            sums[rows, rank[1 << c2]] += long.astype(np.uint32)
                            continue
                        have = rank[(m := sets(b))[m >> c2 & 1 == 1]]
                        columns = have[have >= 0]
                        hubs = int(np.count_nonzero(long > LONG))
                        if hubs:
                            (x,) = read(f"{cut}/s/{p}/{q}-{c2}", np.uint32, 2 * c + 1)
                            put(sums, rows[:hubs], columns, x.reshape(hubs, -1))
                        if hubs < len(rows):
                            ids, x = read(f"{cut}/a/{q}-{c2}", np.uint32)
                            ids, x = ids.view(np.int64), x.reshape(-1, len(have))[:, have >= 0]
                            y = x[np.searchsorted(ids, far[first[hubs:]])]
                            for j in range(1, int(long[hubs])):
                                to = int(np.count_nonzero(long > j)) - hubs
                                y[:to] = added(y[:to], x[np.searchsorted(ids, far[first[hubs : hubs + to] + j])])
                            put(sums, rows[hubs:], columns, y)
                            del x, y
                if cut is None:
                    sums %= np.uint32(prime)
                targets = sets(t - 1, k - 1)
                if keep is None:
                    # the kept part is the vertex itself, with its own colour
                    out = (sums * np.uint64(inverse) % prime).astype(np.uint32) if d > 1 else sums
                else:
                    out = combined(np, table(keep, p, c, a) if n else np.zeros((0, math.comb(k - 1, a - 1)), np.uint32), sums, targets, sets)
                if last:
                    return int(out.sum(dtype=np.int64)) % prime
                if kept_later:
                    write(f"{whole}/{p}-{c}", [out])
                if cut_later:
                    hand_out(out)
                return 0

            def combined(np, kept, sums, targets, sets):
                """For each target the products of the kept counts of its parts with the sums of the rest, added up."""
                place = np.zeros((2, 1 << (k - 1)), np.int32)
                for i, m in enumerate((sets(a - 1, k - 1), sets(b, k - 1))):
                    place[i, m] = np.arange(len(m))
                # the bits of each target, and those of them that go to the kept part
                bits = np.nonzero(targets[:, None] >> np.arange(k - 1) & 1)[1].reshape(len(targets), t - 1)
                chosen = np.array(list(itertools.combinations(range(t - 1), a - 1)), np.int64).reshape(-1, a - 1)
                inside = (1 << bits)[:, chosen].sum(2)
                of_kept, of_sums = place[0][inside], place[1][targets[:, None] - inside]
                splits, n = len(chosen), len(kept)
                out = np.empty((n, len(targets)), np.uint32)
                wide = min(2048, PART // min(splits, SPLITS))
                for lo in range(0, n, wide):
                    x, y = (z[lo : lo + wide].T.astype(np.uint64, order="C") for z in (kept, sums))
                    done = np.empty((len(targets), x.shape[1]), np.uint32)
                    left, right = (np.empty((min(splits, SPLITS), x.shape[1]), np.uint64) for _ in range(2))
                    for i in range(len(targets)):
                        total = None
                        for at in range(0, splits, SPLITS):
                            u, v = of_kept[i, at : at + SPLITS], of_sums[i, at : at + SPLITS]
                            m = len(u)
                            np.take(x, u, 0, out=left[:m], mode="clip")
                            np.take(y, v, 0, out=right[:m], mode="clip")
                            np.multiply(left[:m], right[:m], out=left[:m])
                            part = np.add.reduce(left[:m], 0) % prime
                            total = part if total is None else (total + part) % prime
                        done[i] = total if d == 1 else total * np.uint64(inverse) % prime
                    out[lo : lo + wide] = done.T
                return out

            return work

        return sum(map(int, self._steps(job, k))) % prime
