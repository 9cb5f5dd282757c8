"""Token ids of a public tokenizer: flat binary files and their reader.

``Encoder`` gives the ids that the tokenizers library gives.  Texts are cut at ASCII white space, which
no token of a white-space-dropping tokenizer spans, so a piece's ids are found once and kept in a
bounded memo of two generations; a new word of letters goes to the library's model, any other new piece
to the whole library.

The file format is flat: ``<name>.ids`` holds unsigned little-endian ids without separators, 16 bits
wide where the vocabulary allows and else 32; ``<name>.off`` holds three unsigned 64-bit numbers
for each document, its id, whether it has one, and the offset of its first id, and a last triple for the end.  Both can be memory-mapped.  A file covers a range of ascending doc_ids;
the base of each file is the prefix sum of the files before it.

Defined cases: null and empty texts are the end id alone; equal doc_ids follow each other in the order
of their text's hash; rows without a doc_id come first; a very long text is one row of a batch of bounded
rows; an empty table gives no file and no row; only doc_id and text are read, so other columns may have any name.  Files
of failed task attempts are never named in the manifest.
"""

from __future__ import annotations

import struct
import uuid
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._store import fresh_path, open_file_system, small_batches, written

END_ID = 1
MEMO = 1_600_000
#: Marks that are cut from the ends of a piece; neither those of special tokens nor the apostrophe of contractions.
MARKS = '.,;:!?"()[]{}*$%&#-_=+/~^'
#: Letters below this code point are letters to Python and to the tokenizer alike.
LATIN_END = "\u0250"
_ENCODERS: dict[str, Encoder] = {}


def word_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class Encoder:
    """Ids of whole texts, as bytes of unsigned little-endian integers ``width`` wide."""

    def __init__(self, path: str):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer
        from tokenizers.pre_tokenizers import ByteLevel

        self.tok = Tokenizer.from_file(path)
        self.width = 2 if self.tok.get_vocab_size() <= 1 << 16 else 4
        self.memo: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        self.bytes_of = ByteLevel(add_prefix_space=False, use_regex=False).pre_tokenize_str
        self.split = self._drops_spaces()
        self.bare = self.split and self._models_letters()

    def _drops_spaces(self) -> bool:
        """Whether a text's ids are those of its white-space pieces in turn, tried on texts that would tell."""
        probe = ["a b", "a  b.\n c", "it's 12 'll x", " lead", "trail ", "\t3 4\r\n5", "A, B ! ?", "é è ê", "word's s 's"]
        return all(self._ids([t])[0] == [i for x in self._ids(t.split()) for i in x] for t in probe)

    def _models_letters(self) -> bool:
        """Whether words and the marks around them are tokens apart that the model alone encodes, tried on words that would tell."""
        if self.tok.normalizer is None:
            return False
        words = ["the", "anthonst", "reatonsh", "x", "zzqqxx", "internationalization", "Straße", "ñandú", "ÉLAN", "œuvre", "Ça"]
        alone = all(self._letters(w) == self._pack(self._ids([w])[0]) for w in words)
        return alone and all(self._ids([a + w + b])[0] == [i for x in self._ids([a, w, b]) for i in x] for w in words for a, b in (("", "."), ('"', ',"'), ("(", ").$$$"), ("--", "%")))

    def _ids(self, texts: list[str]) -> list[list[int]]:
        return [e.ids for e in self.tok.encode_batch_fast(texts, add_special_tokens=False)]

    def _pack(self, ids: list[int]) -> bytes:
        return struct.pack(f"<{len(ids)}{'H' if self.width == 2 else 'I'}", *ids)

    def _letters(self, body: str) -> bytes | None:
        """The ids of a word of letters alone, which is one token of the splitter; None where it is not known to be one."""
        if not body.isalpha():
            return None
        if body.isascii():
            unit = body.lower()
        else:
            unit = self.tok.normalizer.normalize_str(body)
            if not unit.isalpha() or max(unit) >= LATIN_END:
                return None
            unit = self.bytes_of(unit)[0][0]
        return self._pack([t.id for t in self.tok.model.tokenize(unit)])

    def _known(self, piece: str) -> bytes | None:
        """From the two generations of the memo; what is still in use moves to the younger one."""
        ids = self.memo.get(piece)
        if ids is None and (ids := self.older.get(piece)) is not None:
            self.memo[piece] = ids
        return ids

    def _learn(self, pieces: list[str]) -> None:
        """Encode new pieces.  A word of letters and the punctuation around it are tokens apart."""
        memo, rest, framed = self.memo, [], []
        for p in pieces:
            body = p.strip(MARKS) if self.bare else ""
            at = p.find(body)
            ids = self._known(body) if body else None
            if body and ids is None and (ids := self._letters(body)) is not None:
                memo[body] = ids
            if ids is None or not body.isalpha():
                rest.append(p)
            elif len(body) < len(p):
                marks = p[:at], p[at + len(body) :]
                framed.append((p, marks, ids))
                rest += [m for m in marks if m and self._known(m) is None]
        rest = list(dict.fromkeys(rest))
        for i in range(0, len(rest), 4096):
            part = rest[i : i + 4096]
            for p, ids in zip(part, self._ids(part)):
                memo[p] = self._pack(ids)
        memo[""] = b""
        for p, (lead, tail), ids in framed:
            memo[p] = memo[lead] + ids + memo[tail]

    def encode(self, texts: pa.Array | list[str | None]) -> list[bytes]:
        import numpy as np

        if not isinstance(texts, pa.Array):
            texts = pa.array(texts, pa.large_string())
        texts = texts.cast(pa.large_string()).fill_null("")
        if not self.split:
            return [self._pack(x) for x in self._ids(texts.to_pylist())]
        # pieces are cut at ASCII white space only: what other characters count as space is the tokenizer's matter
        parts = pc.ascii_split_whitespace(texts)
        coded = parts.flatten().dictionary_encode()
        pieces, codes = coded.dictionary.to_numpy(zero_copy_only=False).tolist(), coded.indices.to_numpy()
        if len(self.memo) > MEMO // 2:
            self.memo, self.older = {}, self.memo
        ids = list(map(self.memo.get, pieces))
        absent = [i for i, x in enumerate(ids) if x is None]
        self._learn([p for i in absent if self._known(p := pieces[i]) is None])
        for i in absent:
            ids[i] = self.memo[pieces[i]]
        # every piece's ids lie once in a pool; the texts are gathered from it
        pool = np.frombuffer(b"".join(ids), f"<u{self.width}")
        sizes = np.fromiter(map(len, ids), np.int64, len(ids)) // self.width
        places = np.cumsum(sizes) - sizes
        long = sizes[codes]
        ends = np.concatenate([[0], np.cumsum(long)])
        flat = pool[np.arange(ends[-1]) + np.repeat(places[codes] - ends[:-1], long)]
        cuts = parts.offsets.to_numpy()
        cuts = ends[cuts - cuts[0]] if len(cuts) else cuts
        return [flat[a:b].tobytes() for a, b in zip(cuts[:-1], cuts[1:])]


def encoder(path: str) -> Encoder:
    """One encoder a worker process; its memo outlives a task."""
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(path)
    return _ENCODERS[path]


MANIFEST = "part int, file string, width int, n_docs long, n_tokens long, first_id long"


def write_tokens(docs: DataFrame, folder: str, tokenizer: str | None = None, end_id: int = END_ID, files: int | None = None) -> DataFrame:
    """Encode all texts and write them in ascending doc_id order; returns the committed manifest."""
    path = tokenizer or word_tokenizer()
    spark = docs.sparkSession
    small_batches(spark)
    n = files or int(spark.conf.get("spark.sql.shuffle.partitions"))
    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    d = d.repartitionByRange(n, F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), F.xxhash64("text"))

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        enc, part = encoder(path), TaskContext.get().partitionId()
        end = enc._pack([end_id])
        name = f"{folder}/tokens-{part:06d}-{uuid.uuid4().hex[:8]}"
        fs, base = open_file_system(name)
        fs.create_dir(base.rsplit("/", 1)[0], recursive=True)
        ids = offsets = None
        total = rows = 0
        first = None
        for batch in batches:
            if not batch.num_rows:
                continue
            if ids is None:
                ids, offsets = (fs.open_output_stream(base + x, compression=None) for x in (".ids", ".off"))
                first = batch.column("doc_id")[0].as_py()
            coded = [x + end for x in enc.encode(batch.column("text"))]
            ids.write(b"".join(coded))
            sizes = np.array([len(x) // enc.width for x in coded], np.uint64)
            starts = np.concatenate([[0], np.cumsum(sizes)[:-1]]).astype(np.uint64) + np.uint64(total)
            doc = batch.column("doc_id")
            keys = doc.fill_null(0).to_numpy(zero_copy_only=False).astype("<i8")
            valid = np.asarray(doc.is_valid()).astype("<i8")
            offsets.write(np.stack([keys.view("<u8"), valid.view("<u8"), starts.astype("<u8")], 1).tobytes())
            total += int(sizes.sum())
            rows += len(coded)
        if ids is not None:
            offsets.write(np.array([0, 0, total], "<u8").tobytes())
            ids.close(), offsets.close()
            yield pa.RecordBatch.from_pylist([{"part": part, "file": name, "width": enc.width, "n_docs": rows, "n_tokens": total, "first_id": first}], pa.schema([("part", pa.int32()), ("file", pa.string()), ("width", pa.int32()), ("n_docs", pa.int64()), ("n_tokens", pa.int64()), ("first_id", pa.int64())]))

    return written(d.mapInArrow(write, MANIFEST), "token-manifest")


def with_bases(manifest: DataFrame) -> DataFrame:
    """The manifest with ``base``: the ids in all files before.  It has one row a file, a few bytes each."""
    spark = manifest.sparkSession
    rows, base, out = sorted(manifest.collect(), key=lambda r: r["part"]), 0, []
    for r in rows:
        out.append((*r, base))
        base += r["n_tokens"]
    return spark.createDataFrame(out, MANIFEST + ", base long")


def read_tokens(manifest: DataFrame) -> DataFrame:
    """(doc_id, start, ids) of every document in the files: ids are unsigned little-endian 32-bit integers."""
    spark = manifest.sparkSession
    m = with_bases(manifest)
    m = m.repartition(max(1, int(spark.conf.get("spark.sql.shuffle.partitions"))), "file")

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for batch in batches:
            for r in batch.to_pylist():
                fs, path = open_file_system(r["file"])
                local = fs.type_name == "local"
                with fs.open_input_file(path + ".off") as f:
                    off = np.frombuffer(f.read(), "<u8").reshape(-1, 3)
                width = "<u2" if r["width"] == 2 else "<u4"
                source = np.memmap(path + ".ids", width, "r") if local else None
                stream = None if local else fs.open_input_file(path + ".ids")
                for i in range(0, len(off) - 1, 500):
                    part = off[i : i + 501]
                    lo, hi = int(part[0, 2]), int(part[-1, 2])
                    if local:
                        data = np.asarray(source[lo:hi])
                    else:
                        stream.seek(lo * r["width"])
                        data = np.frombuffer(stream.read((hi - lo) * r["width"]), width)
                    data = data.astype("<u4")
                    cut = (part[:, 2] - part[0, 2]).astype(np.int64)
                    ids = [data[a:b].tobytes() for a, b in zip(cut[:-1], cut[1:])]
                    doc = pa.array(part[:-1, 0].view("<i8"), pa.int64(), mask=part[:-1, 1] == 0)
                    yield pa.RecordBatch.from_arrays([doc, pa.array(part[:-1, 2].astype(np.int64) + r["base"]), pa.array(ids, pa.binary())], ["doc_id", "start", "ids"])

    return m.mapInArrow(read, "doc_id long, start long, ids binary")


def op9_token_binary(spark, sf_dir: str) -> DataFrame:
    """Write the ids of all documents to flat files and read them back."""
    manifest = write_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet"), fresh_path(spark, "tokens"))
    out = read_tokens(manifest)
    return out.select("doc_id", "start", (F.octet_length("ids") / 4).cast("long").alias("n_tokens"), F.crc32("ids").alias("ids_crc32"))
