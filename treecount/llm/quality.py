"""Quality rules as a ledger of bit masks; native expressions only.

Every rule is evaluated once per document.  The ledger keeps the measurements and one bit per failed
rule, so that a policy (a named, versioned set of rules that reject) is a mask test and an ablation
is one bitwise aggregation, without touching the texts again.

Defined cases: a null text counts as no text; a text without words has zero measurements and fails
``few_words``; repeated rows, and rows that share a doc_id or have none, are judged one by one; windows of
equal words count as one whatever their order; a very long text is measured whole; an empty table gives an
empty ledger.  The ledger has the columns named in ``keep`` and its own; a kept column must not have a
ledger column's name, so callers put rows with any other columns into a struct, as the pipeline does.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SPACES = " \t\n\u000b\f\r"
WORD_GAP = "[\\x20\\x09-\\x0D]+"
NOT_SPACE = "[^\\x20\\x09-\\x0D]"
SYMBOLS = "#*$%&|<>"
WINDOW = 5

#: Bit -> (name, condition that fails a document). Bits 0 and 1 are the base rules.
RULES: tuple[tuple[str, str], ...] = (
    ("few_words", "n_words < 10"),
    ("repeated_words", "100 * n_repeat_words > 20 * n_words"),
    ("symbols", "n_symbols > n_words"),
    ("word_length", "n_words > 0 and (word_chars < n_words * 3 div 2 or word_chars > 40 * n_words)"),
    ("repeated_lines", "n_lines >= 4 and 100 * n_dup_lines > 60 * n_lines"),
)
BASE_BITS = 0b11


@dataclass(frozen=True)
class Policy:
    """A versioned set of rules that reject."""

    name: str
    version: int
    rules: tuple[str, ...] = field(default=tuple(n for n, _ in RULES))

    @property
    def mask(self) -> int:
        bits = {n: 1 << i for i, (n, _) in enumerate(RULES)}
        return sum(bits[r] for r in self.rules)


POLICIES = (
    Policy("base", 1, ("few_words", "repeated_words")),
    Policy("standard", 1),
)


def words(text: Column) -> Column:
    """The words of a text, in order."""
    t = F.btrim(text, F.lit(SPACES))
    return F.when(t == "", F.array().cast("array<string>")).otherwise(F.split(t, WORD_GAP))


def _covered(grams: Column, width: int) -> Column:
    """How many words lie in windows whose hash occurs at least twice; work is O(n log n) in the text."""
    pairs = F.sort_array(F.transform(grams, lambda g, i: F.struct(g.alias("g"), i.alias("i"))))
    same = lambda p: F.filter(
        p, lambda x, j: (F.get(p, j - 1)["g"] == x["g"]) | (F.get(p, j + 1)["g"] == x["g"])
    )
    at = lambda p: F.sort_array(F.transform(p, lambda x: x["i"]))
    gain = lambda p: F.transform(
        p, lambda x, j: F.least(F.lit(width), F.coalesce(F.get(p, j + 1) - x, F.lit(width))).cast("long")
    )
    # one-element arrays bind each intermediate once; a plain reference would compute it again per element
    once = lambda value, f: F.element_at(F.transform(F.array(value), f), 1)
    return once(pairs, lambda p: once(same(p), lambda d: once(at(d), lambda s: F.aggregate(gain(s), F.lit(0).cast("long"), lambda a, x: a + x))))


def measure(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",), text: str = "text") -> DataFrame:
    """One row per document with the measurements the rules need."""
    d = docs.select(*keep, F.coalesce(F.col(text), F.lit("")).alias("_t"))
    d = d.select(
        *keep, "_t", F.transform(words(F.col("_t")), lambda w: F.xxhash64(w)).alias("_h"),
        F.filter(F.split("_t", "\n"), lambda x: x.rlike(NOT_SPACE)).alias("_l"),
    )
    h = F.col("_h")
    gram = lambda i: F.xxhash64(*[F.get(h, i + k) for k in range(WINDOW)])
    none = F.array().cast("array<bigint>")
    d = d.select(
        *keep,
        F.size(h).cast("long").alias("n_words"),
        F.char_length(F.translate("_t", SPACES, "")).cast("long").alias("word_chars"),
        (F.char_length("_t") - F.char_length(F.translate("_t", SYMBOLS, ""))).cast("long").alias("n_symbols"),
        F.size("_l").cast("long").alias("n_lines"),
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"),
        F.when(F.size(h) >= WINDOW, F.transform(F.sequence(F.lit(0), F.size(h) - WINDOW), gram)).otherwise(none).alias("_g"),
    )
    repeated = F.when(F.size(F.array_distinct("_g")) == F.size("_g"), F.lit(0).cast("long")).otherwise(_covered(F.col("_g"), WINDOW))
    return d.select(*keep, "n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", repeated.alias("n_repeat_words"))


def ledger(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",), text: str = "text") -> DataFrame:
    """Measurements plus ``fail_bits``: bit i is set where rule i fails."""
    bits = F.lit(0)
    for i, (_, condition) in enumerate(RULES):
        bits = bits.bitwiseOR(F.when(F.expr(condition), F.lit(1 << i)).otherwise(F.lit(0)))
    return measure(docs, keep, text).withColumn("fail_bits", bits)


def verdict(policy: Policy, bits: str = "fail_bits") -> Column:
    """True where a policy keeps the document."""
    return F.col(bits).bitwiseAND(F.lit(policy.mask)) == 0


def ablation(book: DataFrame, policies: tuple[Policy, ...] = POLICIES) -> DataFrame:
    """Per policy and rule: documents that fail it, fail it alone, and would come back without it.

    One pass over the ledger: the bits are counted by distinct mask, of which there are at most
    2^rules, and everything else is arithmetic on those few rows.
    """
    spark = book.sparkSession
    masks = book.groupBy("fail_bits").agg(F.count("*").alias("n"))
    plan = [(p.name, p.version, p.mask, n, 1 << i) for p in policies for i, (n, _) in enumerate(RULES) if p.mask & (1 << i)]
    rules = spark.createDataFrame(plan, "policy string, version int, mask int, rule string, bit int")
    hit = F.expr("fail_bits & mask")
    return masks.crossJoin(F.broadcast(rules)).groupBy("policy", "version", "rule").agg(
        F.sum("n").alias("n_docs"),
        F.sum(F.when(F.expr("(fail_bits & bit) <> 0"), F.col("n")).otherwise(0)).alias("n_failed"),
        F.sum(F.when(hit == F.col("bit"), F.col("n")).otherwise(0)).alias("n_only"),
        F.sum(F.when(hit != 0, F.col("n")).otherwise(0)).alias("n_rejected"),
    )


def op8_quality_rules(spark, sf_dir: str) -> DataFrame:
    """The ledger of all documents with the base verdict and that of the standard policy."""
    book = ledger(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    base = F.col("fail_bits").bitwiseAND(F.lit(BASE_BITS)) != 0
    return book.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        base.alias("base_failed"), (~base & verdict(POLICIES[1])).alias("kept"),
        F.col("fail_bits").cast("long").alias("fail_bits"),
    )


SQL = r"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, text, list_filter(regexp_split_to_array(text, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w,
             list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM t),
g AS (SELECT doc_id, unnest(range(1, len(w) - 3)) AS i, w FROM w WHERE len(w) >= 5),
h AS (SELECT doc_id, i, array_to_string(w[i:i + 4], ' ') AS s FROM g),
r AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, s) AS n FROM h) WHERE n > 1),
c AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM r, range(5) AS q(k) GROUP BY doc_id),
m AS (SELECT w.doc_id, len(w)::BIGINT AS n_words,
             coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::BIGINT AS word_chars,
             (length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
             len(l)::BIGINT AS n_lines, (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines,
             coalesce(c.n, 0)::BIGINT AS n_repeat_words FROM w LEFT JOIN c ON c.doc_id = w.doc_id),
f AS (SELECT *, (n_words < 10)::INT + 2 * (100 * n_repeat_words > 20 * n_words)::INT + 4 * (n_symbols > n_words)::INT
             + 8 * (n_words > 0 AND (word_chars < n_words * 3 // 2 OR word_chars > 40 * n_words))::INT
             + 16 * (n_lines >= 4 AND 100 * n_dup_lines > 60 * n_lines)::INT AS bits FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
       (bits & 3) <> 0 AS base_failed, bits = 0 AS kept, bits::BIGINT AS fail_bits FROM f
"""
