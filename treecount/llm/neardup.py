"""Near-duplicate documents: one-permutation hashing with optimal densification, banded, in stars.

Words are runs of other than ASCII white space with A-Z lowered; a document's set holds the hashes of
its distinct word shingles (one of the whole sequence below ``WORDS`` words).  One permutation sends
the set into ``SLOTS`` bins; an empty bin borrows from a filled one that a fixed chain of hash probes
finds (optimal densification).  ``ROWS`` slots make a bucket key.

Documents with equal sets are one class and only its least document goes on.  In a bucket every
member is compared with one centre, the member that meets most others over all its buckets, so the
pairs are as many as the members.  Two such rounds, confirmed on the full sets, join nearly all of a
group.  What is still apart though it shares a bucket is compared in blocks of bounded size inside the
tasks: there the common members of all full sets are counted by matrix products, and only links between
components leave a task, so its rows grow with the components and no pair is passed over.  Components follow by contraction.

Defined cases: null or wordless texts have an empty set and are linked with nothing; repeated rows
are linked as equal texts; rows that share a doc_id are one document with several texts and linked by
each of them; rows without a doc_id are returned unlinked; ties go to the least doc_id; a very long text
is one row of a batch of bounded rows, its set held whole; an empty table gives an empty result.  Only
doc_id and text are read, so other columns may have any name.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._graph import components
from ._store import forget, scratch, small_batches, written

WORDS = 5
PERCENT = 85
BANDS = 40
ROWS = 8
#: Members and set members of a block of a bucket.
BLOCK = 512
BLOCK_HASHES = 4_000_000
#: Sets up to this size are also compared wherever they share a shingle of their prefix, so none of their links is lost.
SMALL = 32


def prefix_keys(hashes, percent: int = PERCENT):
    """Keys of which two sets that have ``percent`` of their union in common, one with ``SMALL`` members at most, share one."""
    import numpy as np

    n = len(hashes)
    if percent <= 0 or n * percent > SMALL * 100:
        return np.zeros(0, np.int64)
    return (hashes[: n - -(-percent * n // 100) + 1] ^ np.uint64(0xA5A5A5A5A5A5A5A5)).view(np.int64)


def shingle_hashes(text: str | None, words: int = WORDS, memo: dict | None = None):
    """Sorted distinct 64-bit hashes (numpy uint64) of a text's word shingles."""
    import numpy as np
    import xxhash

    parts = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not parts:
        return np.zeros(0, np.uint64)
    if memo is None:
        memo = {}
    if len(memo) > 400_000:
        memo.clear()
    out = []
    for w in parts:
        h = memo.get(w)
        if h is None:
            h = memo[w] = xxhash.xxh3_64_intdigest(w)
        out.append(h)
    h = np.array(out, np.uint64)
    n = max(1, len(h) - words + 1)
    acc = np.full(n, len(parts) if len(parts) < words else words, np.uint64)
    with np.errstate(over="ignore"):
        for k in range(min(words, len(h))):
            acc = (acc ^ h[k : k + n]) * np.uint64(0x9E3779B97F4A7C15)
            acc ^= acc >> np.uint64(29)
        acc *= np.uint64(0xBF58476D1CE4E5B9)
        acc ^= acc >> np.uint64(32)
    return np.unique(acc)


class Sketcher:
    """Signatures of ``slots`` one-permutation minima."""

    def __init__(self, bands: int = BANDS, rows: int = ROWS):
        import numpy as np

        self.bands, self.rows, self.slots = bands, rows, bands * rows
        # probe chains of the empty bins: column j lists the bins that bin j asks in turn
        k = np.arange(64 * self.slots, dtype=np.uint64).reshape(64, self.slots)
        with np.errstate(over="ignore"):
            k = (k + np.uint64(0x51ED270B)) * np.uint64(0x9E3779B97F4A7C15)
            k ^= k >> np.uint64(31)
            k *= np.uint64(0x94D049BB133111EB)
            k ^= k >> np.uint64(30)
        self.chain = (k % np.uint64(self.slots)).astype(np.int64)
        self.orders: dict = {}
        self.salt = np.arange(bands, dtype=np.uint64)

    def signature(self, hashes):
        import numpy as np

        bins = ((hashes >> np.uint64(32)) * np.uint64(self.slots) >> np.uint64(32)).astype(np.int64)
        first = np.flatnonzero(np.diff(bins, prepend=-1))
        sig, full = np.zeros(self.slots, np.uint64), np.zeros(self.slots, bool)
        sig[bins[first]], full[bins[first]] = hashes[first], True
        empty = np.flatnonzero(~full)
        if len(empty):
            probes = full[self.chain[:, empty]]
            step = probes.argmax(0)
            donor = self.chain[step, empty]
            for at in np.flatnonzero(~probes[step, np.arange(len(empty))]):  # a full permutation always finds one
                order = self.order(empty[at])
                donor[at] = order[full[order].argmax()]
            sig[empty] = sig[donor]
        return sig

    def order(self, slot: int):
        """All bins, in the order in which a slot asks them once its chain has ended."""
        import numpy as np

        if slot not in self.orders:
            self.orders[slot] = np.random.default_rng(int(slot)).permutation(self.slots)
        return self.orders[slot]

    def keys(self, sig):
        import numpy as np

        s = sig.reshape(self.bands, self.rows)
        with np.errstate(over="ignore"):
            acc = (self.salt + np.uint64(1)) * np.uint64(0xD6E8FEB86659FD93)
            for r in range(self.rows):
                acc = (acc ^ s[:, r]) * np.uint64(0x9E3779B97F4A7C15)
                acc ^= acc >> np.uint64(32)
        return acc.view(np.int64)


def sketches(docs: DataFrame, words: int = WORDS, bands: int = BANDS, rows: int = ROWS, percent: int = PERCENT) -> DataFrame:
    """(doc_id, n_shingles, set_id, keys): set_id is a 128-bit hash of the set."""
    small_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np
        import xxhash

        sketcher, memo = Sketcher(bands, rows), {}
        for batch in batches:
            n, ids, keys = [], [], []
            for text in batch.column("text").to_pylist():
                h = shingle_hashes(text, words, memo)
                n.append(len(h))
                if len(h):
                    sig = sketcher.signature(h)
                    ids.append(xxhash.xxh3_128_digest(h.tobytes()))
                    keys.append(np.concatenate([sketcher.keys(sig), prefix_keys(h, percent)]))
                else:
                    ids.append(None), keys.append(None)
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id").cast(pa.int64()), pa.array(n, pa.int64()), pa.array(ids, pa.binary()), pa.array(keys, pa.list_(pa.int64()))],
                ["doc_id", "n_shingles", "set_id", "keys"],
            )

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_shingles long, set_id binary, keys array<long>")


def full_sets(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """(doc_id, set_id, h): the whole set, recomputed from the text."""
    small_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        memo: dict = {}
        for batch in batches:
            sets = [shingle_hashes(t, words, memo) for t in batch.column("text").to_pylist()]
            ids = [xxhash.xxh3_128_digest(h.tobytes()) for h in sets]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").cast(pa.int64()), pa.array(ids, pa.binary()), pa.array([h.view("int64") for h in sets], pa.list_(pa.int64()))], ["doc_id", "set_id", "h"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, set_id binary, h array<long>")


def _star(rows: DataFrame, weight: DataFrame) -> DataFrame:
    """(a, b): each member of a bucket with the member of largest weight; rows: (k, id, c) with a component c."""
    w = rows.join(weight, "id")
    hub = w.groupBy("k").agg(F.max(F.struct("w", (-F.col("id")).alias("i"), "c")).alias("m"), F.count("*").alias("n")).where("n > 1")
    hub = hub.select("k", (-F.col("m.i")).alias("a"), F.col("m.c").alias("ca"))
    return rows.join(hub, "k").where("c <> ca").select("a", F.col("id").alias("b"))


def common_counts(sets: list):
    """Matrix of the numbers of common members of each two sets (arrays of distinct integers)."""
    import numpy as np

    n = len(sets)
    out = np.zeros((n, n), np.float64)
    owner = np.repeat(np.arange(n), [len(x) for x in sets])
    _, number, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    shared = times[number] > 1  # what one set alone has is common to none
    owner, number = owner[shared], number[shared]
    order = np.argsort(number, kind="stable")
    owner, number = owner[order], np.unique(number[order], return_inverse=True)[1]
    width = 4096
    for lo in range(0, int(number[-1]) + 1 if len(number) else 0, width):
        part = slice(*np.searchsorted(number, (lo, lo + width)))
        m = np.zeros((n, width), np.float32)
        m[owner[part], number[part] - lo] = 1
        out += m @ m.T
    return out


def block_links(ids, comp, sets: list, percent: int, side=None):
    """Links that join all components that any pair of the sets links; with ``side`` only pairs of different sides count."""
    import numpy as np

    size = np.array([len(x) for x in sets], np.float64)
    common = common_counts(sets)
    ok = (100 * common >= percent * (size[:, None] + size[None, :] - common)) & (comp[:, None] != comp[None, :])
    if side is not None:
        ok &= side[:, None] != side[None, :]
    parent: dict = {}

    def top(x):
        while parent.get(x, x) != x:
            x = parent[x]
        return x

    out = []
    for i, j in zip(*np.nonzero(np.triu(ok, 1))):
        a, b = top(comp[i]), top(comp[j])
        if a != b:
            parent[max(a, b)] = min(a, b)
            out.append((ids[i], ids[j]))
    return out


def _blocks(rows: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """(a, b): links between different components that share a bucket; rows: (k, id, c).

    A bucket is cut into blocks of about ``BLOCK`` members and ``BLOCK_HASHES`` set members; a task compares two blocks.
    """
    sized = sets.select(F.col("doc_id").alias("id"), F.size("h").cast("long").alias("n")).groupBy("id").agg(F.sum("n").alias("n"))
    size = rows.join(sized, "id").groupBy("k").agg(F.count("*").alias("m"), F.sum("n").alias("n"), F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo <> hi")
    parts = F.greatest(F.ceil(F.col("m") / BLOCK), F.ceil(F.col("n") / BLOCK_HASHES)).cast("int")
    r = rows.join(size.select("k", parts.alias("p")), "k").withColumn("i", F.pmod(F.xxhash64("id"), F.col("p")).cast("int"))
    r = r.withColumn("j", F.explode(F.sequence(F.lit(0), F.col("p") - 1))).join(sets.select(F.col("doc_id").alias("id"), "h"), "id")
    r = r.select("k", F.least("i", "j").alias("x"), F.greatest("i", "j").alias("y"), "i", "id", "c", "h")

    def compare(table: pa.Table) -> pa.Table:
        ids, comp, block = (table.column(c).to_numpy() for c in ("id", "c", "i"))
        sets = [x.values.to_numpy(zero_copy_only=False) for x in table.column("h")]
        apart = table.column("x")[0].as_py() != table.column("y")[0].as_py()
        found = block_links(ids, comp, sets, percent, block if apart else None)
        return pa.table({"a": pa.array([x for x, _ in found], pa.int64()), "b": pa.array([y for _, y in found], pa.int64())})

    return r.groupBy("k", "x", "y").applyInArrow(compare, "a long, b long")


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs whose full sets have at least ``percent`` of their union in common."""
    pairs = written(pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "candidates")
    p = pairs.join(sets.select(F.col("doc_id").alias("b"), F.col("h").alias("hb")), "b")
    p = p.join(sets.select(F.col("doc_id").alias("a"), F.col("h").alias("ha")), "a")
    p = p.select("a", "b", F.size("ha").alias("na"), F.size("hb").alias("nb"), F.size(F.array_intersect("ha", "hb")).alias("n"))
    return p.where(100 * F.col("n") >= percent * (F.col("na") + F.col("nb") - F.col("n"))).select("a", "b")


def near_duplicates(docs: DataFrame, words: int = WORDS, percent: int = PERCENT, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) of every row of ``docs``."""
    with scratch(docs.sparkSession) as keep:
        member, label = map(keep, _classes(docs, words, percent, bands, rows))
    out = member.join(label.select(F.col("id").alias("rep"), "component"), "rep", "left")
    out = out.select("doc_id", "n_shingles", F.coalesce("component", "rep", "doc_id").alias("component_id"))
    return out.withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def _classes(docs: DataFrame, words: int, percent: int, bands: int, rows: int) -> tuple[DataFrame, DataFrame]:
    """(doc_id, n_shingles, rep) of every row and (id, component) of the representatives that are linked to others."""
    sk = written(sketches(docs, words, bands, rows, percent), "sketches")
    # equal sets: one class each, kept by its least document; written, so that the joins with large classes can be split
    same = written(sk.where("doc_id is not null and n_shingles > 0").groupBy("set_id").agg(F.min("doc_id").alias("rep")), "classes")
    reps = sk.join(same.select(F.col("rep").alias("doc_id"), "set_id"), ["doc_id", "set_id"], "left_semi").dropDuplicates(["doc_id", "set_id"])
    reps = written(reps.select(F.col("doc_id").alias("id"), "keys"), "representatives")
    member = written(sk.select("doc_id", "n_shingles", "set_id").join(same, "set_id", "left").select("doc_id", "n_shingles", "rep"), "members")
    forget(sk)
    # several texts of one doc_id
    several = member.where("rep is not null").groupBy("doc_id").agg(F.min("rep").alias("a"), F.max("rep").alias("_z")).where("a <> _z").select("doc_id", "a")
    links = written(member.join(several, "doc_id").where("a <> rep").select("a", F.col("rep").alias("b")).distinct(), "links")
    every = reps.select("id", F.explode("keys").alias("k")).distinct()
    full = written(every.groupBy("k").agg(F.count("*").alias("n")).where("n > 1"), "shared-keys")
    met = written(every.join(full, "k").select("k", "id", "n"), "buckets")
    weight = written(met.groupBy("id").agg(F.sum("n").alias("w")), "weights")
    wanted = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(weight.select(F.col("id").alias("doc_id")), "doc_id", "left_semi")
    sets = written(full_sets(wanted, words).dropDuplicates(["doc_id", "set_id"]), "sets")
    label = components(links)
    for step in ("first star", "second star", "main blocks", "blocks"):
        r = met.select("k", "id").join(label.select("id", "component"), "id", "left").select("k", "id", F.coalesce("component", "id").alias("c"))
        live = r.groupBy("k").agg(F.count("*").alias("n"), F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo <> hi").select("k", "n")
        r = written(r.join(live, "k"), "live-buckets")
        if r.isEmpty():
            break
        if step == "first star":
            found = _confirmed(_star(r, weight), sets, percent)
        elif step == "second star":
            # from a member outside the first centre's component
            top = r.join(weight, "id").groupBy("k").agg(F.max(F.struct("w", (-F.col("id")).alias("i"), "c")).alias("m")).select("k", F.col("m.c").alias("top"))
            second = r.join(top, "k").where("c <> top").join(weight, "id").groupBy("k").agg(F.max(F.struct("w", (-F.col("id")).alias("i"), "c")).alias("m"))
            second = second.select("k", (-F.col("m.i")).alias("a"), F.col("m.c").alias("ca"))
            found = _confirmed(r.join(second, "k").where("c <> ca").select("a", F.col("id").alias("b")), sets, percent)
        elif step == "main blocks":
            # each member's largest bucket: what is joined there need not be compared in its other buckets
            largest = r.groupBy("id").agg(F.max(F.struct("n", "k")).alias("m")).select(F.col("m.k").alias("k"))
            main = written(largest.distinct(), "main-keys")
            found = _blocks(r.join(main, "k", "left_semi").select("k", "id", "c"), sets, percent)
        else:
            found = _blocks(r.join(main, "k", "left_anti").select("k", "id", "c"), sets, percent)
        links = links.union(written(found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "links"))
        label = components(links)
    return member, label


def op5_minhash_near_dedup(spark, sf_dir: str) -> DataFrame:
    """Near-duplicate components of all documents."""
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))


SQL = r"""
WITH RECURSIVE t AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
         '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
        ELSE list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) END AS g FROM t),
n AS (SELECT doc_id, len(g)::BIGINT AS n_shingles FROM s),
x AS MATERIALIZED (SELECT doc_id, hash(unnest(g)) AS h FROM s),
p AS MATERIALIZED (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM x a JOIN x b ON a.h = b.h AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS MATERIALIZED (SELECT a, b FROM p JOIN n u ON u.doc_id = a JOIN n v ON v.doc_id = b WHERE 100 * c >= 85 * (u.n_shingles + v.n_shingles - c)),
e AS MATERIALIZED (SELECT a, b FROM l UNION SELECT b, a FROM l),
r AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, e.b FROM r JOIN e ON r.b = e.a),
m AS (SELECT a AS doc_id, min(b) AS component_id FROM r GROUP BY 1)
SELECT n.doc_id, n_shingles, component_id, n.doc_id = component_id AS kept FROM n JOIN m ON m.doc_id = n.doc_id
"""
