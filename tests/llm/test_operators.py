"""Each operator against a brute-force version on a small table with the odd cases."""

import base64
import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers as P
import pytest

from treecount.llm import bytebpe, fingerprints, linededup, lmscore, neardup, packing, privacy, quality, tokens, warc

BASE = "one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen sixteen seventeen eighteen nineteen twenty " * 3
LONG = " ".join(f"w{i * 7919 % 1000}x{i}" for i in range(4000))
TEXTS = [
    BASE, BASE, BASE.replace("ten", "TEN"), BASE + "extra words", None, "", "   \n\t ", "short one", "a b c d e", LONG, LONG + " tail", "x" * 5000,
    "mail a.b@c.org and a@b.c_d@e.f\nip 10.0.0.300 1.2.3.4.5 0001.02.3.255", "card 4111 1111 1111 1111, call +1 (415) 555-2671 é +44 20 7946 0958",
    "déjà vu — naïve ﬁ 日本語テキスト 🙂  double  space\r\n", "line a is here\nline a is here\n\nother line entirely\nline a is here", "it's we'll 12345 <|endoftext|> #*$%",
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i * 3, t, "en", "s", len(t or "")) for i, t in enumerate(TEXTS)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(3)


def by_id(df, key="doc_id"):
    return {r[key]: r for r in df.collect()}


def test_quality(docs):
    got = by_id(quality.ledger(docs))
    for i, t in enumerate(TEXTS):
        w = [x for x in re.split(r"[\x20\x09-\x0D]+", t or "") if x]
        n = Counter(tuple(w[j : j + 5]) for j in range(len(w) - 4))
        covered = {j + k for j in range(len(w) - 4) if n[tuple(w[j : j + 5])] > 1 for k in range(5)}
        lines = [x for x in (t or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        r = got[i * 3]
        assert (r.n_words, r.word_chars, r.n_repeat_words, r.n_dup_lines) == (len(w), sum(map(len, w)), len(covered), len(lines) - len(set(lines)))
        assert r.n_symbols == sum(c in "#*$%&|<>" for c in t or "")
    assert {r["rule"] for r in quality.ablation(quality.ledger(docs)).collect()} == {n for n, _ in quality.RULES}


def test_warc(spark):
    rows = [(1, "u1", "x" * 2000), (2, None, "x" * 2000), (3, "u3", None), (4, "u4", "small"), (5, "u5", "small"), (6, "u6", "é" * 900)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    index = warc.write_bundles(warc.plan_records(pages), warc.fresh_path(spark, "test"))
    got = by_id(warc.read_bundles(index), "page_id")
    for p, _, h in rows:
        raw = (h or "").encode()
        assert (got[p].payload_bytes, got[p].payload_digest) == (len(raw), hashlib.sha1(raw).hexdigest())
        assert got[p].record_type == "response" and got[p].payload == raw if p != 1 else (got[p].record_type, got[p].refers_to) == ("revisit", 2)
    assert {r.page_id for r in warc.read_records(index.where("page_id in (3, 6)")).collect()} == {3, 6}
    assert warc.read_bundles(warc.write_bundles(warc.plan_records(pages.limit(0)), warc.fresh_path(spark, "test"))).count() == 0


def test_near_duplicates(docs):
    got = by_id(neardup.near_duplicates(docs))
    sets = {}
    for i, t in enumerate(TEXTS):
        w = (t or "").encode().lower().split()
        sets[i * 3] = {tuple(w[j : j + 5]) for j in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    label = {d: d for d in sets}
    for _ in sets:
        for a in sets:
            for b in sets:
                if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 85 * len(sets[a] | sets[b]):
                    label[a] = label[b] = min(label[a], label[b])
    for d, s in sets.items():
        assert (got[d].n_shingles, got[d].component_id, got[d].kept) == (len(s), label[d], label[d] == d)


def test_lines(docs):
    got = by_id(linededup.dedup_lines(docs))
    assert len(got) == len(TEXTS)
    assert got[45].text == "line a is here\n\nother line entirely"  # the copies of its first line go
    assert got[3].text == "" and got[0].text == BASE and got[12].text is None and got[18].text == TEXTS[6]
    assert got[6].text == "" and got[9].text == ""  # near copies of the first line of the corpus


def base_of(t):
    out, n = [], [0] * 4
    kinds = [("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")]
    for k, (kind, pattern) in enumerate(kinds):
        for m in re.finditer(pattern, t):
            ds = re.sub("[^0-9]", "", m[0])
            luhn = sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(reversed(ds))) % 10 == 0
            if {"email": True, "ip": kind == "ip" and all(int(x) <= 255 for x in m[0].split(".")), "card": 14 <= len(ds) <= 19 and luhn, "phone": 10 <= len(ds) <= 15}[kind]:
                n[k] += 1
                out.append((m.start(), k, m.end()))
    return n, ",".join(f"{kinds[k][0]}:{a}:{b}" for a, k, b in sorted(out))


def test_privacy(spark, docs):
    from pyspark.sql import functions as F

    lines = [(100 + i, f"the secretword {i} belongs to boss@firm.example really n{i}") for i in range(5)] + [(200 + i, "really the belongs plain text") for i in range(40)]
    every = docs.select("doc_id", "text").union(spark.createDataFrame(lines, "doc_id long, text string"))
    d = privacy.find(every, ["doc_id"])
    base = F.concat(*[F.col(f"_{k}") for k in privacy.KINDS])
    got = by_id(d.select("doc_id", "_t", privacy.listed(base).alias("base"), privacy.listed(F.col("_terms")).alias("terms"), *[F.size(f"_{k}").alias(k) for k in privacy.KINDS]))
    for r in got.values():
        assert ([r[k] for k in privacy.KINDS], r.base) == base_of(r["_t"])
    assert got[100].terms.startswith("term:4:14") and got[200].terms == ""
    clean = by_id(privacy.sanitise(every))
    assert "boss@firm" not in clean[100].text and "secretword" not in clean[100].text and clean[200].text == "really the belongs plain text"
    assert clean[12].text is None


def test_fingerprints(docs):
    got = by_id(fingerprints.compare_with_next(docs))
    order = sorted(got, reverse=True)
    text = {i * 3: t or "" for i, t in enumerate(TEXTS)}
    for i, d in enumerate(order):
        nxt = order[(i + 1) % len(order)]
        k = len(text[d]) // 3
        edited = text[d][: len(text[d]) - k] + text[nxt][:k]
        assert (got[d].n_chars, got[d].edited_sha256) == (len(text[d]), hashlib.sha256(edited.encode()).hexdigest())
    assert got[0].fingerprint == got[3].fingerprint and got[3].near_next == 1.0


def test_packing_and_tokens(spark, docs):
    from pyspark.sql import functions as F
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    want = {i * 3: [*tok.encode(t or "", add_special_tokens=False).ids, 1] for i, t in enumerate(TEXTS)}
    manifest = tokens.write_tokens(docs, tokens.fresh_path(spark, "test"))
    at = 0
    for r in sorted(tokens.read_tokens(manifest).collect(), key=lambda r: r.doc_id):
        assert (r.start, np.frombuffer(r.ids, "<u4").tolist()) == (at, want[r.doc_id])
        at += len(want[r.doc_id])
    pieces = packing.pack(docs, window=64).withColumn("crc", F.crc32("ids")).collect()
    seen, used = {}, {}
    for p in pieces:
        seen.setdefault(p.doc_id, []).append((p.start, np.frombuffer(p.ids, "<u4").tolist()))
        used.setdefault(p.sequence_id, []).append((p.offset, p.length))
        assert p.crc == zlib.crc32(p.ids)
    assert {d: [x for _, ids in sorted(v) for x in ids] for d, v in seen.items()} == want
    for v in used.values():
        end = 0
        for offset, length in sorted(v):
            assert offset == end
            end += length
        assert end <= 64
    assert sorted(used) == list(range(len(used)))


def test_plan_uses_every_piece_once():
    h = {700: 5, 649: 5, 33: 7, 2047: 1, 1: 1, 1024: 4}
    steps = packing.plan(h)
    assert all(sum(k * n for k, n in take.items()) <= 2048 for _, take in steps)
    total = Counter()
    for times, take in steps:
        total.update({k: n * times for k, n in take.items()})
    assert total == h and packing.padding(steps) < 2048 * 3


def test_byte_bpe(docs):
    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(P.path("byte_bpe_multi_50k.tiktoken"), "rb"))}
    e = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got = by_id(bytebpe.decode(bytebpe.encode(docs)))
    for i, t in enumerate(TEXTS):
        assert np.frombuffer(got[i * 3].ids, "<u4").tolist() == e.encode_ordinary(t or "")
        assert bytes(got[i * 3].raw) == (t or "").encode()


def test_scores_prefer_what_was_seen(spark):
    rng = np.random.default_rng(1)
    chain = {a: rng.permutation(30)[:3] for a in range(30)}

    def text(shuffled):
        out, a = [], 0
        for _ in range(300):
            out.append(f"v{a}")
            a = int(rng.choice(chain[a]))
        return " ".join(rng.permutation(out) if shuffled else out)

    train = spark.createDataFrame([(i, text(False)) for i in range(120)], "doc_id long, text string")
    top = lmscore.vocabulary(train)
    params = lmscore.train(train, top, rounds=4)
    held = spark.createDataFrame([(i, text(i % 2 == 1)) for i in range(10)] + [(99, None)], "doc_id long, text string")
    got = by_id(lmscore.score(held, top, params))
    assert got[99].n_words == 0 and got[99].log_likelihood == 0
    assert min(got[i].log_likelihood for i in range(0, 10, 2)) > max(got[i].log_likelihood for i in range(1, 10, 2))
    assert lmscore.train(train.limit(0), top) is None


def test_encoder_equals_the_library_on_odd_texts():
    from treecount.llm.tokens import Encoder, word_tokenizer

    odd = ["", None, "  ", "<|endoftext|>", "a<|endoftext|>b .<|startoftext|>.", "it's 'tis don't. \"can't\"", "İstanbul ΣΑΣ. ſ ß", "été, ≠ x≠", "日本語、 12,5 a1b", "\x1c\x1d a", "...word...", "(Ça)$$$", "ﬁn ŉ", "x́.", "’s it’s", "ª º", "a\x00b", "--"]
    enc = Encoder(word_tokenizer())
    expected = [enc._pack(ids) for ids in enc._ids([t or "" for t in odd])]
    assert enc.bare and enc.encode(odd) == expected and enc.encode(odd) == expected
    enc.memo, enc.older = {}, enc.memo  # a new generation still finds what the older one knows
    assert enc.encode(odd) == expected
    assert enc.encode([]) == []


def test_lines_that_differ_by_one_letter_or_by_spaces(spark):
    first = "the committee will publish its annual report on regional transport before the end of june this year"
    rows = [(1, first), (2, first.replace("annual", "annuel")), (3, first.replace("report on", "report \t on")), (4, "short"), (5, "shorn")]
    got = by_id(linededup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")))
    assert [got[i].text for i in range(1, 6)] == [first, "", "", "short", "shorn"]


def test_scores_predict_the_word_itself(spark):
    common = " ".join(f"f{i}" for i in range(lmscore.TOP + 9))  # more than have a class of their own
    rows = [(100 + i, common) for i in range(12)] + [(10, "aarest"), (11, "Bbrest")] + [(20 + i, "bbrest") for i in range(3)] + [(30, None), (31, "bbrest bbrest"), (31, "bbrest bbrest")]
    out = lmscore.score_corpus(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    got = {r.doc_id: r.log_likelihood for r in out}
    assert len(out) == len(rows) and got[30] == 0
    assert abs(got[11] - got[20]) < 1e-3 and abs(got[11] - got[10] - np.log(8)) < 1e-3  # one class, 1 and 8 occurrences
    assert len({r.log_likelihood for r in out if r.doc_id == 31}) == 1


def test_training_covers_every_position(monkeypatch):
    texts = ["w0", "w1 w2", " ".join(f"w{i}" for i in range(3, 30)), None, ""]
    seen = []
    monkeypatch.setattr(lmscore.Net, "learn", lambda self, context, target, rate: seen.extend(target.tolist()))
    top = [f"w{i}" for i in range(30)]
    classes = lmscore.Classes(top)
    context, target, starts = lmscore.windows([x for t in texts if len(x := classes.of(t))])
    lmscore.Net().learn(context, target, 0.1)
    assert Counter(seen) == {i: 1 for i in range(30)} and list(starts) == [0, 1, 3, 30]
    assert [int(c[0]) for c in context] == [lmscore.EDGE] * 4 and [int(c[1]) for c in context] == [lmscore.EDGE, lmscore.EDGE, 2, lmscore.EDGE]


def test_network_is_a_distribution_and_equals_brute_force():
    net = lmscore.Net()
    rng = np.random.default_rng(0)
    context = [rng.integers(0, lmscore.CLASSES, 3) for _ in range(2 * lmscore.SIDE)]
    total, embed = np.zeros(3), net.views[0]
    for c in range(lmscore.CLASSES):
        p = net.log_probabilities(context, np.full(3, c))
        total += np.exp(p.astype(float))
        if c % 97 == 0:
            for i in range(3):
                a = np.maximum(sum(embed[k][context[k][i]] for k in range(4)) + net.views[1], 0)
                soft = lambda z: np.exp(z - z.max()) / np.exp(z - z.max()).sum()
                g = c // lmscore.WIDTH
                want = np.log(soft(a @ net.views[2] + net.views[3])[g] * soft(a @ net.views[4][g] + net.views[5][g])[c % lmscore.WIDTH])
                assert abs(want - p[i]) < 1e-4
    assert np.allclose(total, 1, atol=1e-4)


def test_training_does_not_depend_on_the_split(spark):
    rows = [(i, f"a{i % 7} b{i % 5} c{i % 3} d a{i % 4}" * 3) for i in range(200)]
    d = spark.createDataFrame(rows, "doc_id long, text string")
    top = lmscore.vocabulary(d)
    one, two = (lmscore.train(d.repartition(n), top, replica=2000) for n in (1, 7))
    assert np.allclose(one, two, atol=1e-6) and not np.allclose(one, lmscore.Net().params)


def test_privacy_judges_rare_entities_and_copies(spark):
    plain = [(i, f"ordinary sentence number{i} about weather") for i in range(300)]
    once = [(1000, "ordinary codename owner x@y.example about weather")]
    copied = [(2000 + i, f"ordinary undercover n{i % 3} boss@z.example about weather") for i in range(300)]
    d = privacy.find(spark.createDataFrame(plain + once + copied, "doc_id long, text string"), ["doc_id"])
    got = {r.doc_id: {r["_t"][s.start : s.end] for s in r["_terms"]} for r in d.select("doc_id", "_t", "_terms").collect()}
    assert got[1000] == {"codename", "owner"} and got[2000] == {"undercover"} and got[0] == set()


def test_short_near_copies_are_all_candidates():
    rng = np.random.default_rng(3)
    sketcher = neardup.Sketcher()
    for _ in range(3000):
        h = rng.integers(0, 2**63, 7).astype(np.uint64) * np.uint64(2)
        a, b = np.sort(h), np.sort(h[:6])
        keys = [set(sketcher.keys(sketcher.signature(x)).tolist()) | set(neardup.prefix_keys(x).tolist()) for x in (a, b)]
        assert keys[0] & keys[1]
    few = np.sort(rng.integers(0, 2**63, 1).astype(np.uint64))
    assert set(sketcher.signature(few)) == set(few)
