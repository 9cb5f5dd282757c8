"""Personal data: patterns, and terms that reveal them; native expressions only.

The patterns find e-mail addresses, IP addresses, card numbers (Luhn) and telephone numbers; each kind
is matched leftmost and without overlap, and a match that fails its check is dropped.  The patterns are
the plain ones made possessive and anchored at the start of a run, which gives the same matches in
linear time on any text.

The values found are the protected entities.  The corpus tells which other terms reveal one: with the
line as the unit, the pointwise mutual information of term and entity, as a share of the entity's own
information, says how much of the entity a term discloses.  The share of a term's lines that have the
entity is smoothed by ``SMOOTH`` lines without it, so that little evidence counts for less but counts.
Terms at or above ``THRESHOLD`` are disclosing: those that disclose all of it, as counted, are removed,
the others generalised to a class label.

Counting: terms, entities, pairs and the corpus are all counted in distinct lines, so copies of one line
are one piece of evidence.  All are aggregations with map-side combining.

Defined cases: null texts are empty; repeated rows and rows that share a doc_id are treated each, rows
without one too; an empty table, or one without entities, has no disclosing term; spans of equal start go
by kind; a very long text is matched whole, in linear time, its spans gathered in one array; other columns
of the table are left as they are, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._store import scratch, written

KINDS = ("email", "ip", "card", "phone")
#: Fixed patterns, in the order of KINDS; (?<!..) and \G start a match where a run starts or the last match ended.
PATTERNS = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: A text without these cannot match.
NEEDS = {"email": "@", "ip": r"[0-9]\.[0-9]+\.[0-9]", "card": r"[0-9][\x20-]?[0-9]", "phone": r"\+[0-9]"}
TERM = r"\p{L}{4,}"
THRESHOLD = 0.8
SMOOTH = 1.0
#: Disclosing terms up to this number go to the tasks as a set; more are joined by a shuffle.
BROADCAST_TERMS = 200_000
LABELS = {k: f"[{k.upper()}]" for k in KINDS}
GENERAL = "[TERM]"


def _once(value: Column, f) -> Column:
    return F.element_at(F.transform(F.array(value), f), 1)


def _luhn(digits: Column) -> Column:
    n = F.char_length(digits)
    ds = F.transform(F.sequence(F.lit(1), n), lambda i: F.substring(digits, i, F.lit(1)).cast("int") * (F.lit(1) + F.pmod(n - i, F.lit(2))))
    total = F.aggregate(ds, F.lit(0), lambda a, x: a + F.when(x > 9, x - 9).otherwise(x))
    return F.pmod(total, F.lit(10)) == 0


def _valid(kind: str, value: Column) -> Column:
    if kind == "email":
        return F.lit(True)
    if kind == "ip":
        part = lambda p: _once(F.regexp_replace(p, "^0+", ""), lambda q: (F.char_length(q) <= 3) & (F.coalesce(q.try_cast("int"), F.lit(0)) <= 255))
        return F.forall(F.split(value, r"\."), part)
    digits = F.regexp_replace(value, "[^0-9]", "")
    if kind == "phone":
        return F.char_length(digits).between(10, 15)
    return _once(digits, lambda d: F.when(F.char_length(d).between(14, 19), _luhn(d)).otherwise(F.lit(False)))


SPAN = "array<struct<start:int,rank:int,end:int,value:string>>"


def _places(text: Column, pattern: str, rank: int, wanted=None) -> Column:
    """Spans of the matches of a pattern, in code points; ``wanted`` keeps some by their value."""

    def walk(found: Column, gaps: Column) -> Column:
        start = F.struct(F.lit(0).alias("at"), F.array().cast(SPAN).alias("out"))

        def step(acc: Column, m: Column) -> Column:
            begin = acc["at"] + F.char_length(m["gap"])
            end = begin + F.char_length(m["hit"])
            one = F.array(F.struct(begin.alias("start"), F.lit(rank).alias("rank"), end.alias("end"), m["hit"].alias("value")))
            keep = F.lit(True) if wanted is None else wanted(m["hit"])
            return F.struct(end.alias("at"), F.when(keep, F.concat(acc["out"], one)).otherwise(acc["out"]).alias("out"))

        pairs = F.zip_with(found, F.slice(gaps, F.lit(1), F.size(found)), lambda h, g: F.struct(h.alias("hit"), g.alias("gap")))
        return F.aggregate(pairs, start, step, lambda acc: acc["out"])

    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    return _once(found, lambda f: F.when(F.size(f) == 0, F.array().cast(SPAN)).otherwise(walk(f, F.split(text, pattern, -1))))


def _checked(kind: str, spans: Column) -> Column:
    return F.filter(spans, lambda s: _valid(kind, s["value"]))


def base_spans(text: Column) -> dict[str, Column]:
    """Checked spans of each kind."""
    out = {}
    for rank, kind in enumerate(KINDS):
        need = F.contains(text, F.lit("@")) if kind == "email" else text.rlike(NEEDS[kind])
        spans = _checked(kind, _places(text, PATTERNS[kind], rank))
        out[kind] = F.when(need, spans).otherwise(F.array().cast(SPAN))
    return out


def detect(docs: DataFrame, keep: list[str], text: str = "text") -> DataFrame:
    """``keep``, the text as ``_t``, and an array of spans for each kind."""
    d = docs.select(*keep, F.coalesce(F.col(text), F.lit("")).alias("_t"))
    return d.select(*keep, "_t", *[c.alias(f"_{k}") for k, c in base_spans(F.col("_t")).items()])


def _terms(line: Column) -> Column:
    return F.transform(F.array_distinct(F.regexp_extract_all(F.lower(line), F.lit(TERM), F.lit(0))), lambda w: F.xxhash64(w))


def disclosing_terms(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(term, disclosure): hashes of the terms that reveal a protected entity, by the most they reveal of one (1: all of it)."""
    with scratch(docs.sparkSession) as keep:
        return keep(_disclosing(docs, threshold))


def _disclosing(docs: DataFrame, threshold: float) -> DataFrame:
    line = F.explode(F.split(F.coalesce(F.col("text"), F.lit("")), "\n"))
    every = docs.select(line.alias("text"))
    hit = every.where(F.col("text").contains("@") | F.col("text").rlike("[0-9][0-9\\x20().-]{5,}"))
    found = detect(hit, [])
    value = F.transform(F.concat(*[F.col(f"_{k}") for k in KINDS]), lambda s: F.xxhash64(s["rank"], F.lower(s["value"])))
    rest = F.regexp_replace("_t", PATTERNS["email"], " ")  # words inside an address are no evidence about it
    found = found.select(F.xxhash64("_t").alias("line"), _terms(rest).alias("terms"), F.array_distinct(value).alias("entities")).where(F.size("entities") > 0)
    found = written(found.dropDuplicates(["line"]), "entity-lines")
    entity = found.select("line", F.explode("entities").alias("entity"))
    n_entity = written(entity.groupBy("entity").agg(F.count("*").alias("ne")), "entities")
    # summed by entity and term before the join, so that a frequent entity's lines never meet in one task
    pairs = found.select("terms", F.explode("entities").alias("entity")).select("entity", F.explode("terms").alias("term"))
    pairs = pairs.groupBy("entity", "term").agg(F.count("*").alias("nj"))
    pairs = written(pairs.join(n_entity, "entity").select("entity", "ne", "term", "nj"), "entity-terms")
    if pairs.isEmpty():
        return written(pairs.select("term", F.lit(0.0).alias("disclosure")), "disclosing-terms")
    # one line of each text, by its hash; in the entities' lines the words inside an address do not count
    once = every.groupBy(F.xxhash64("text")).agg(F.first("text").alias("text"))
    rest = F.when(F.contains("text", F.lit("@")), F.regexp_replace("text", PATTERNS["email"], " ")).otherwise(F.col("text"))
    counts = once.select(F.explode(_terms(rest)).alias("term")).groupBy("term").agg(F.count("*").alias("nt"))
    counts = counts.join(pairs.select("term").distinct(), "term", "left_semi")
    total = every.select(F.xxhash64("text")).distinct().count()
    j = pairs.join(counts, "term")
    information = F.log(F.lit(float(total)) / F.col("ne"))
    shared = F.log(F.col("nj") * F.lit(float(total)) / (F.col("ne").cast("double") * (F.col("nt") + F.lit(SMOOTH))))
    d = F.when(information > 0, shared / information).otherwise(F.lit(0.0))
    j = j.select("term", d.alias("d"), (F.col("nj") == F.col("nt")).alias("all")).where(F.col("d") >= threshold)
    return written(j.groupBy("term").agg(F.max(F.when(F.col("all"), F.lit(1.0)).otherwise(F.least("d", F.lit(0.999)))).alias("disclosure")), "disclosing-terms")


def _hits(docs: DataFrame, risky: DataFrame) -> DataFrame | None:
    """(_id, _risky): for each document with disclosing terms, those it has; None where there are none at all."""
    n = risky.count()
    if not n:
        return None
    r = risky.select("term", F.col("disclosure"))
    r = F.broadcast(r) if n <= BROADCAST_TERMS else r
    t = docs.select(F.col("doc_id").alias("_id"), F.explode(_terms(F.coalesce(F.col("text"), F.lit("")))).alias("term")).join(r, "term")
    return t.groupBy("_id").agg(F.collect_set("term").alias("_risky"), F.collect_set(F.when(F.col("disclosure") >= 1.0, F.col("term"))).alias("_gone"))


def find(docs: DataFrame, keep: list[str], threshold: float = THRESHOLD) -> DataFrame:
    """``keep`` and ``_t``, the base spans by kind, ``_terms`` (spans of disclosing terms) and ``_gone`` (those to remove)."""
    hits = _hits(docs, disclosing_terms(docs, threshold))
    if hits is None:
        d = docs.withColumns({"_risky": F.lit(None).cast("array<bigint>"), "_gone": F.lit(None).cast("array<bigint>")})
    else:
        d = docs.join(hits, docs["doc_id"].eqNullSafe(hits["_id"]), "left")
    d = detect(d, [*keep, "_risky", "_gone"])
    spans = _places(F.col("_t"), TERM, len(KINDS), lambda w: F.array_contains("_risky", F.xxhash64(F.lower(w))))
    base = F.concat(*[F.col(f"_{k}") for k in KINDS])
    free = lambda s: ~F.exists(base, lambda b: (s["start"] < b["end"]) & (b["start"] < s["end"]))
    terms = F.when(F.col("_risky").isNotNull(), F.filter(spans, free)).otherwise(F.array().cast(SPAN))
    return d.select(*keep, "_t", *[f"_{k}" for k in KINDS], "_gone", terms.alias("_terms"))


def listed(spans: Column) -> Column:
    """``kind:start:end`` of spans by start, then kind, joined by commas."""
    names = F.array(*[F.lit(k) for k in (*KINDS, "term")])
    return F.array_join(F.transform(F.sort_array(spans), lambda s: F.concat_ws(":", F.get(names, s["rank"]), s["start"].cast("string"), s["end"].cast("string"))), ",")


def sanitise(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """``docs`` with personal data replaced by labels and disclosing terms generalised or removed in ``text``."""
    names = docs.columns
    own = F.struct(*[F.col(f"`{c}`") for c in names]).alias("own")  # apart from the columns made here, whatever their names
    d = find(docs.select(own, "doc_id", "text"), ["own"], threshold)
    labels = F.array(*[F.lit(LABELS[k]) for k in KINDS], F.lit(GENERAL))
    spans = F.sort_array(F.concat(*[F.col(f"_{k}") for k in KINDS], F.col("_terms")))

    def step(acc: Column, s: Column) -> Column:
        # a span that overlaps the one before only lengthens what is cut
        apart = s["start"] >= acc["at"]
        gone = (s["rank"] == len(KINDS)) & F.coalesce(F.array_contains("_gone", F.xxhash64(F.lower(s["value"]))), F.lit(False))
        label = F.when(gone, F.lit("")).otherwise(F.get(labels, s["rank"]))
        piece = F.concat(F.substring(F.col("_t"), acc["at"] + 1, s["start"] - acc["at"]), label)
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), F.when(apart, F.concat(acc["out"], piece)).otherwise(acc["out"]).alias("out"))

    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))
    new = F.aggregate(spans, start, step, lambda acc: F.concat(acc["out"], F.substring(F.col("_t"), acc["at"] + 1, F.char_length("_t") - acc["at"])))
    text = F.when(F.size(spans) == 0, F.col("own")["text"]).otherwise(new)
    return d.select(*[(text if c == "text" else F.col("own").getField(c)).alias(c) for c in names])


def op3_information_pii(spark, sf_dir: str) -> DataFrame:
    """Personal data and disclosing terms of all documents."""
    d = find(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"), ["doc_id"])
    base = F.concat(*[F.col(f"_{k}") for k in KINDS])
    return d.select(
        "doc_id", *[F.size(f"_{k}").cast("long").alias(f"n_{k}") for k in KINDS],
        F.sha2(listed(base), 256).alias("base_sha256"), listed(F.concat(base, F.col("_terms"))).alias("spans"),
        F.size("_terms").cast("long").alias("n_term"),
    )
