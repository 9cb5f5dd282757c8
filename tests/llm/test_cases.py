"""Fuzzy components against all pairs, and the odd cases of every operator and pipeline stage."""

import hashlib
import re
from collections import Counter
from itertools import combinations

import numpy as np
import pytest
import regex
from pyspark.sql import functions as F

import corpus_pipeline
from treecount.llm import bytebpe, fingerprints, linededup, neardup, quality, queries, warc

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
CLASH = ["_t", "_l", "_h", "n_words", "fail_bits", "_drop", "gone", "own", "row", "n_removed", "_email", "_terms", "_risky", "_gone", "_id", "ids", "k", "h", "id", "rep", "a.b"]


def components(items, linked):
    parent = {i: i for i in items}

    def top(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in combinations(sorted(items), 2):
        if linked(a, b):
            x, y = top(a), top(b)
            parent[max(x, y)] = min(x, y)
    return {i: top(i) for i in items}


def edited(rng, text, n):
    out = list(text)
    for _ in range(n):
        out[int(rng.integers(len(out)))] = chr(97 + int(rng.integers(26)))
    return "".join(out)


def test_lines_equal_all_pairs(spark):
    rng = np.random.default_rng(5)
    word = lambda: "".join(chr(97 + int(c)) for c in rng.integers(0, 26, int(rng.integers(3, 9))))
    base = [" ".join(word() for _ in range(int(rng.integers(3, 40)))) for _ in range(40)]
    texts = base + [edited(rng, b, n) for b in base for n in (1, 1, 2, 3, 5)]
    shared = " ".join(word() for _ in range(25))
    texts += [f"{shared} {word()} {word()} {word()} {word()}" for _ in range(60)]  # one bucket, similarities about the threshold
    texts += ["ab", "ab ", "a", "\U0001F642" * 9, "é" * 30, "-" * 50, "-" * 51]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string").repartition(3)
    line = {r.line_id: r.line for r in linededup.lines(docs).collect()}
    units = lambda t: t.encode("utf-16-be")
    sets = {i: {units(t)[j : j + 16] for j in range(0, max(1, len(units(t)) - 15), 2)} for i, t in line.items()}
    want = components(list(line), lambda a, b: len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]))
    got = {r.id: r.component for r in linededup.links(docs, linededup.sketch(docs)).collect()}
    assert sum(got.get(i, i) != c for i, c in want.items()) <= 1  # bands miss a pair at the threshold with probability 0.0008
    assert len(set(want.values())) < len(want) - 50


def test_rows_that_share_a_doc_id_keep_their_own_lines(spark):
    rows = [(1, "the very first line of all\nsecond line here"), (2, "something else altogether\nthe very first line of all"), (2, "the very first line of all\nsomething new again"), (None, "something new again"), (None, None)]
    out = linededup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string"))
    got = sorted((r.doc_id or 0, r.text or "", r.n_removed) for r in out.collect())
    assert got == [(0, "", 0), (0, "something new again", 0), (1, "the very first line of all\nsecond line here", 0), (2, "", 2), (2, "something else altogether", 1)]


def words_of(t):
    w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate({c: c + 32 for c in range(65, 91)}))
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def brute(texts):
    sets = {i: words_of(t) for i, t in texts.items()}
    return components(list(texts), lambda a, b: bool(sets[a]) and bool(sets[b]) and 100 * len(sets[a] & sets[b]) >= 85 * len(sets[a] | sets[b]))


def test_near_duplicates_of_every_size(spark, monkeypatch):
    monkeypatch.setattr(neardup, "BLOCK", 16)  # several blocks a bucket
    rng = np.random.default_rng(2)
    texts, n = {}, 0
    for size in (4, 5, 9, 10, 11, 12, 20, 33, 40, 60, 150, 400):
        base = [f"s{size}w{i}" for i in range(size)]
        for k in range(12):
            w = list(base)
            for _ in range(k % 4):
                w[int(rng.integers(size))] = f"x{n}"
            texts[n := n + 1] = " ".join(w)
    for k in range(60):  # a chain: neighbours are alike, the ends are not
        texts[n := n + 1] = " ".join(f"c{i}" for i in range(3 * k, 3 * k + 60))
    texts[n := n + 1], texts[n := n + 1] = None, " \t"
    got = {r.doc_id: r for r in neardup.near_duplicates(spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(5)).collect()}
    assert {i: r.component_id for i, r in got.items()} == brute(texts)
    assert all(r.n_shingles == len(words_of(texts[i])) and r.kept == (i == r.component_id) for i, r in got.items())


def test_block_links_join_what_pairs_link():
    rng = np.random.default_rng(4)
    base = rng.integers(0, 2**62, 200)
    sets = [np.unique(np.concatenate([base[: 200 - k], rng.integers(0, 2**62, k)])) for k in rng.integers(0, 30, 50)]
    ids = np.arange(50)
    common = neardup.common_counts(sets)
    assert all(common[i, j] == len(np.intersect1d(sets[i], sets[j])) for i, j in combinations(range(50), 2))
    want = components(list(range(50)), lambda a, b: 100 * common[a, b] >= 85 * (len(sets[a]) + len(sets[b]) - common[a, b]))
    found = {frozenset(map(int, x)) for x in neardup.block_links(ids, ids, sets, 85)}
    assert components(list(range(50)), lambda a, b: frozenset((a, b)) in found) == want


def test_several_texts_of_one_doc_id(spark):
    a, b = (" ".join(f"{c}{i}" for i in range(50)) for c in "ab")
    rows = [(5, a), (5, b), (9, b + " more"), (3, a + " more"), (5, a), (None, a), (None, b)]
    got = {(r.doc_id, r.component_id) for r in neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect() if r.doc_id}
    assert got == {(5, 3), (9, 3), (3, 3)}


def test_ablation(spark):
    book = spark.createDataFrame([(b,) for b in (0, 0, 1, 2, 3, 3, 4, 16, 31)], "fail_bits int")
    bits = [0, 0, 1, 2, 3, 3, 4, 16, 31]
    for r in quality.ablation(book).collect():
        policy = next(p for p in quality.POLICIES if p.name == r.policy and p.version == r.version)
        bit = 1 << [n for n, _ in quality.RULES].index(r.rule)
        assert (r.n_docs, r.n_failed, r.n_only, r.n_rejected) == (9, sum(b & bit > 0 for b in bits), sum(b & policy.mask == bit for b in bits), sum(b & policy.mask > 0 for b in bits))


def test_likeness_follows_the_true_similarity(spark):
    rng = np.random.default_rng(6)
    words = lambda: Counter(f"w{int(x)}" for x in rng.integers(0, 80, 150))
    text = lambda c: " ".join(w for w, n in c.items() for _ in range(n))
    counts = [words()]
    for _ in range(60):  # each shares a part with the one before
        cut = int(rng.integers(20, 150))
        kept = list(counts[-1].elements())
        rng.shuffle(kept)
        counts.append(Counter(kept[:cut]) + Counter(list(words().elements())[cut:]))
    docs = spark.createDataFrame([(i, text(c)) for i, c in enumerate(counts)], "doc_id long, text string")
    true = lambda a, b: sum((a & b).values()) / sum((a | b).values())
    for samples in (fingerprints.SAMPLES,):
        # the standard error of one likeness is at most this; all share the samples, so their mean square strays too
        off = 0.5 / np.sqrt(samples)
        got = {r.doc_id: r for r in fingerprints.compare_with_next(docs, samples).collect()}
        errors = []
        for i, c in enumerate(counts):
            following = counts[i - 1]
            errors.append(got[i].near_next - true(c, following))
            n = len(text(c))
            k = n // 3
            edited = Counter((text(c)[: n - k] + text(following)[:k]).split())
            errors.append(got[i].near_edited - true(c, edited))
        assert abs(np.mean(errors)) < off and np.sqrt(np.mean(np.square(errors))) < 1.3 * off, samples


def test_damaged_records_are_noticed():
    raw = warc.encode_record(1, "http://a", b"payload" * 200, hashlib.sha1(b"payload" * 200).hexdigest(), None)
    assert warc.decode_record(raw)[0]["payload"] == b"payload" * 200
    with pytest.raises(ValueError):
        warc.decode_record(raw.replace(b"payloadpayload", b"payloadpayloaD", 1))


def test_any_pattern_is_cut_as_it_says():
    pattern = r"[a-z]+ [a-z]+|."
    ours, plain = bytebpe.Codec(bytebpe.multi_ranks(), pattern), bytebpe.Codec(bytebpe.multi_ranks(), pattern)
    text = "one two three four.\nfive six"
    known = {t: plain.merge([t.encode()])[0] for t in regex.findall(pattern, text)}
    assert ours.encode([text]) == [b"".join(known[t] for t in regex.findall(pattern, text))]


# -- odd tables -----------------------------------------------------------------------------------

ODD = [
    (1, "plain words that make one good line of text for this test\nand another line", "en", "s", 3), (1, "plain words that make one good line of text for this test\nand another line", "en", "s", 3),
    (1, "other text under the same number with enough words to stay in\nthe set", "en", "s", 1), (None, "no number but plenty of words in this one so that it stays", None, None, None), (None, None, None, None, None),
    (2, None, "en", "s", 0), (3, "", "en", "s", 0), (4, " \t\n ", "en", "s", 4), (5, "mail a.b@c.org from 10.0.0.1 about the quarterly numbers of the firm today", "en", "s", 9),
    (6, " ".join(f"long{i}" for i in range(5_000)), "en", "s", 1),
]


@pytest.fixture(scope="module")
def odd(spark):
    d = spark.createDataFrame(ODD, SCHEMA).repartition(2)
    return d.select("*", *[F.lit(i).alias(c) for i, c in enumerate(CLASH)])


@pytest.mark.parametrize("name", [n for n, _ in corpus_pipeline.STAGES])
def test_stage_on_odd_rows_and_names(spark, odd, name):
    stage = dict(corpus_pipeline.STAGES)[name]
    out = stage(spark, odd, "")
    rows = out.collect()
    if name != "pack":
        assert out.columns == odd.columns
        assert all([r[c] for c in CLASH] == list(range(len(CLASH))) for r in rows)
    if name in ("line_dedup", "personal_data"):
        assert len(rows) == len(ODD)
    if name == "personal_data":
        assert any(r.text and "[EMAIL]" in r.text and "[IP]" in r.text and r.n_chars == len(r.text) for r in rows)
    if name == "quality_rules":
        book = {(r.doc_id, r.text) for r in rows}
        assert (6, ODD[-1][1]) in book and (2, None) not in book and (3, "") not in book
    empty = stage(spark, odd.limit(0), "")
    assert empty.columns == out.columns and empty.count() == 0


def test_pipeline_runs_on_a_folder(spark, tmp_path):
    spark.createDataFrame(ODD, SCHEMA).write.parquet(str(tmp_path / "documents.parquet"))
    out = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert out and all(0 < r.length <= 2048 and len(r.ids) == 4 * r.length for r in out)
    for doc in {r.doc_id for r in out if r.doc_id not in (None, 1)}:
        pieces = sorted((r.start, r.length, r.doc_tokens) for r in out if r.doc_id == doc)
        assert pieces[0][0] == 0 and sum(p[1] for p in pieces) == pieces[0][2]
        assert all(a + n == b for (a, n, _), (b, _, _) in zip(pieces, pieces[1:]))


EMPTY_HERE = ("op1_warc", "op4_weighted_fingerprints", "op7_byte_bpe", "op9_token_binary", "op10_masked_lm_score")


@pytest.mark.parametrize("name", sorted(queries.QUERIES))
def test_queries_on_empty_and_odd_tables(spark, tmp_path, name):
    for k, rows in enumerate(([], ODD) if name in EMPTY_HERE else (ODD,)):  # stages test the others' empty tables
        d = tmp_path / str(k)
        spark.createDataFrame(rows, SCHEMA).withColumn("own", F.lit(1)).withColumn("_t", F.lit(2)).write.parquet(str(d / "documents.parquet"))
        spark.createDataFrame([(r[0], "u", r[1]) for r in rows], "page_id long, url string, html string").write.parquet(str(d / "pages.parquet"))
        out = queries.QUERIES[name](spark, str(d)).collect()
        if name == "op6_min_slack_packing":
            assert len(out) >= len(rows)
        else:
            assert len(out) == len(rows)


def test_stages_leave_no_tables_behind_and_settle_pairs_by_size(spark, monkeypatch):
    from treecount.llm import _store

    asked = []
    monkeypatch.setattr(linededup, "confirmed", lambda pairs, text, s, f=linededup.confirmed: (asked.append(pairs.count()), f(pairs, text, s))[1])
    # lines of one run of letters share their least hashes or not; a line five times as long never is like another
    head = "the quick brown fox jumps over the lazy dog and runs away from it "
    docs = spark.createDataFrame([(i, head * (1 + i % 2) + f"{head[::-1]}{i * 7919} " * (i % 2 * 6)) for i in range(12)], "doc_id long, text string")
    made = []
    monkeypatch.setattr(_store, "fresh_path", lambda s, n, f=_store.fresh_path: made.append(f(s, n)) or made[-1])
    out = linededup.dedup_lines(docs)
    kept = [p for p in made if spark._jvm.java.io.File(p.removeprefix("file://")).exists()]
    assert len(made) > 5 and len(kept) == 1 and "dropped-lines" in kept[0]
    assert out.count() == 12 and sum(r.n_removed for r in out.collect()) >= 5
    nothing = spark.createDataFrame([], "a long, b long")
    from treecount.llm._graph import components

    assert components(nothing).columns == ["id", "component"] and components(nothing).count() == 0


def test_gaps_in_lines(spark):
    texts = ["Ab  c", "a\tb", " a b ", "a \x0b b", "\r", "a\x0cb", "É  Z", "plain line", "   "]
    got = [r.line for r in linededup.lines(spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")).orderBy("doc_id").collect()]
    assert got == ["ab c", "a b", "a b", "a b", "a b", "é z", "plain line"]


def test_the_normal_form_is_computed_once_for_a_line(spark):
    plan = linededup.lines(spark.createDataFrame([(1, "A  b")], "doc_id long, text string"))._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("regexp_replace") == 1
