"""Operators that judge row by row: fertility, byte BPE, language, quality, personal data."""

import base64
import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from fieldpress.llm import bpe, fertility, langid, pii, quality
from fieldpress.llm import queries as Q

RANKS = P.path("byte_bpe_50k.tiktoken")
PIECES = P.path("piece_bpe_32k.model")


@pytest.fixture(scope="module")
def library():
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS, "rb"))}
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


# -- op1 -------------------------------------------------------------------------------------


def base_of(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    lines = [x for x in (text or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    windows = [tuple(words[i : i + 8]) for i in range(len(words) - 7)]
    n, hit = Counter(windows), set()
    for i, w in enumerate(windows):
        if n[w] > 1:
            hit.update(range(i, i + 8))
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines) - len(set(lines)), len(hit)


def test_base_counts_are_those_of_the_brute_force(spark, sf, docs, odd):
    want = {r.doc_id: base_of(r.text) for r in docs.collect()}
    got = {r.doc_id: (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in Q.op1_fertility(spark, sf).collect()}
    assert got == want
    for r in fertility.measure(odd, PIECES).collect():
        if r.doc_id == 1:
            assert (r.n_words, r.n_tokens, r.script) == (0, 0, "none")
    rows = {r.doc_id: r for r in fertility.judge(fertility.measure(odd.where("doc_id <> 5"), PIECES)).collect()}
    texts = {r.doc_id: r.text for r in odd.collect()}
    for i, r in rows.items():
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == base_of(texts[i])
    assert not rows[1].kept and rows[1].base_failed and rows[6].base_failed


@settings(max_examples=50, deadline=None)
@given(st.lists(st.integers(0, 3), max_size=60))
def test_repeated_windows(codes):
    want, windows = set(), [tuple(codes[i : i + 8]) for i in range(len(codes) - 7)]
    for i, w in enumerate(windows):
        if windows.count(w) > 1:
            want.update(range(i, i + 8))
    assert fertility.repeated_window_words(np.array(codes, np.int64)) == len(want)


def test_fertility_measures(spark):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=PIECES)
    text = "The quick brown fox jumps over the lazy dog 𓀀 𓀀"
    r = fertility.measure(spark.createDataFrame([(1, text)], "doc_id long, text string"), PIECES).first()
    ids = [i for w in text.split() for i in sp.encode(w)]
    p = np.array(list(Counter(ids).values())) / len(ids)
    assert r.n_tokens == len(ids) and r.chars_per_token == pytest.approx(sum(map(len, text.split())) / len(ids))
    assert r.fallback_share == pytest.approx(sum(sp.is_byte(i) for i in ids) / len(ids)) and r.fallback_share > 0
    assert r.token_entropy == pytest.approx(float(-(p * np.log2(p)).sum()))


def test_bands_by_language(spark, docs):
    m = fertility.measure(docs, PIECES, lang_col="lang")
    bands = fertility.fit_bands(m)
    assert set(bands) == {"en", "de", "fr", "es"}
    kept = fertility.judge(m, bands, key="lang")
    assert kept.where("n_words >= 20 AND kept").count() > 0.8 * kept.where("NOT base_failed").count()
    odd = fertility.judge(m, {"en": fertility.Band((50.0, 60.0), 0, 99)}, key="lang")
    assert odd.where("lang = 'en' AND kept").count() == 0
    assert fertility.measure(docs.where("false"), PIECES).count() == 0
    rank = fertility.measure(docs.limit(3), RANKS).collect()
    assert all(r.n_tokens > 0 for r in rank)


def test_random_letters_fail_fitted_bands(spark, docs):
    rng = np.random.default_rng(5)
    junk = [(10**6 + i, " ".join("".join(rng.choice(list("abcdefghijklmnopqrstuvwxyz"), 7)) for _ in range(200)), "en") for i in range(5)]
    m = fertility.measure(docs.select("doc_id", "text", "lang").union(spark.createDataFrame(junk, "doc_id long, text string, lang string")), PIECES, lang_col="lang")
    rows = fertility.judge_fitted(m, least=10).collect()
    assert not any(r.kept for r in rows if r.doc_id >= 10**6)
    passed = [r for r in rows if r.doc_id < 10**6 and not r.base_failed]
    assert sum(r.kept for r in passed) > 0.8 * len(passed)


# -- op3 -------------------------------------------------------------------------------------


def test_encoding_is_the_librarys(spark, sf, docs, odd, library, none):
    for df in (docs, odd.where("doc_id <> 5")):
        texts = {r.doc_id: r.text or "" for r in df.collect()}
        for r in bpe.encode(df, RANKS, P.PATTERN).collect():
            ids = library.encode_ordinary(texts[r.doc_id])
            assert r.token_ids == ids and r.n_tokens == len(ids) and r.round_trip
            assert r.ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
            assert r.decoded_sha256 == hashlib.sha256(texts[r.doc_id].encode()).hexdigest()
    assert bpe.encode(none, RANKS, P.PATTERN).count() == 0


@settings(max_examples=60, deadline=None)
@given(st.text(max_size=80))
def test_encoding_of_any_text(text):
    coder = test_encoding_of_any_text.__dict__.setdefault("coder", bpe.Coder(RANKS, P.PATTERN))
    lib = test_encoding_of_any_text.__dict__.setdefault("lib", tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=coder.ranks, special_tokens={}))
    text = text.encode("utf-8", "replace").decode()
    assert np.frombuffer(coder.encode(text), np.uint32).tolist() == lib.encode_ordinary(text)
    assert coder.decode(coder.encode(text)).decode() == text


def test_long_pieces_take_the_heap():
    ranks = bpe.read_ranks(RANKS)
    rng = np.random.default_rng(0)
    for alphabet in (b"ab", b"the quick"):
        word = bytes(rng.choice(list(alphabet), 600).tolist())
        long, bpe.LONG = bpe.LONG, 10**9
        try:
            want = bpe.merge(word, ranks)
        finally:
            bpe.LONG = long
        assert bpe.merge_long(word, ranks) == want
    assert b"".join({i: p for p, i in ranks.items()}[i] for i in bpe.merge(b"x" * 200_000, ranks)) == b"x" * 200_000


def test_decode_and_fold_in_higher_order_functions(spark, docs, library):
    enc = bpe.encode(docs.limit(20), RANKS, P.PATTERN)
    texts = {r.doc_id: r.text for r in docs.collect()}
    for r in bpe.decode(enc, RANKS).collect():
        assert bytes(r.decoded).decode() == texts[r.doc_id]
    words = [" the", "onion", " ßüé", "x", " thontion", ""]
    df = spark.createDataFrame([(w,) for w in words], "w string")
    got = {r.w: r.ids for r in df.select("w", bpe.fold_words(F.col("w"), bpe.read_ranks(RANKS)).alias("ids")).collect()}
    for w in words:
        assert got[w] == library.encode_ordinary(w), w


# -- op4 -------------------------------------------------------------------------------------


def slow_grams(text):
    t = "".join(c if c.isalpha() else " " for c in (text or "").lower())
    t = " " + re.sub(" +", " ", t).strip() + " " if t.strip() else ""
    out = Counter(c for c in t if c != " ")
    for n in (2, 3):
        out.update(t[i : i + n] for i in range(len(t) - n + 1))
    return out


def test_grams_are_those_of_the_brute_force():
    for text in ("", None, "...", "Ab", "The cat, the hat. ÄÖ 12 ß", "a-b  c"):
        keys, counts = langid.grams(text)
        mine = {}
        for k, n in zip(keys.tolist(), counts.tolist()):
            chars = [x for x in (k >> 42, k >> 21 & (1 << 21) - 1, k & (1 << 21) - 1) if x]
            mine["".join(" " if x == 1 else chr(x) for x in chars)] = n
        assert mine == dict(slow_grams(text))


def test_languages_of_held_out_documents(spark, sf, docs, odd, none):
    truth = {r.doc_id: r.lang for r in docs.collect()}
    rows = Q.op4_rank_order_langid(spark, sf).collect()
    assert len(rows) == docs.count() and all(0 <= r.score <= 1 for r in rows)
    for r in rows:
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0)
    held = [r for r in rows if r.held_out]
    assert np.mean([r.lang_pred == truth[r.doc_id] for r in held]) > 0.95
    profiles = langid.learn(docs)
    got = {r.doc_id: r for r in langid.identify(odd, profiles).collect()}
    assert got[1].lang_pred == got[2].lang_pred == got[3].lang_pred == "und" and got[1].score == 0
    assert langid.identify(none, profiles).count() == 0
    nothing = langid.learn(none)
    assert {r.lang_pred for r in langid.identify(odd, nothing).collect()} == {"und"}


# -- op6 -------------------------------------------------------------------------------------


def test_pairwise_identity():
    m = quality.Machine(50)
    idx, val = np.array([3, 7, 20], np.int32), np.array([0.5, -1.0, 2.0], np.float32)
    slow = sum(float(m.v[idx[a]] @ m.v[idx[b]]) * val[a] * val[b] for a in range(3) for b in range(a + 1, 3))
    assert m.margin(idx, val) == pytest.approx(slow, abs=1e-6)


def test_quality_of_held_out_documents(spark, sf, odd, none):
    rows = Q.op6_factorisation_quality(spark, sf).collect()
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in rows)
    held = [r for r in rows if r.held_out and r.doc_id in labels]
    assert held and np.mean([r.predicted == labels[r.doc_id] for r in held]) > 0.8
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    m = Q.quality_machine(spark, docs, sf)
    assert quality.score(odd, m).count() == odd.count() and quality.score(none, m).count() == 0
    kept = quality.keep_good(odd, m, 0.0)
    assert kept.columns == odd.columns and kept.count() == odd.count()
    same = {r.doc_id for r in quality.keep_good(docs, m, 0.7).collect()}
    assert same == {r.doc_id for r in rows if r.predicted}


def test_quality_with_metadata_and_without_labels(spark, docs, none):
    labels = spark.createDataFrame([(i, i % 2) for i in range(40)], "doc_id long, quality int")
    m = quality.learn(docs, labels, metadata=("n_chars",))
    assert quality.score(docs, m).count() == docs.count()
    assert quality.keep_good(docs, m, 0.0).count() == docs.count()
    empty = quality.learn(docs, labels.where("false"))
    assert {round(r.score, 1) for r in quality.score(docs.limit(5), empty).collect()} == {0.5}


# -- op8 -------------------------------------------------------------------------------------


def slow_spans(t):
    out = [(m.start(), 0, "email", m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [(m.start(), 1, "ip", m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(x) <= 255 for x in m.group().split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = re.sub("[^0-9]", "", m.group())
        if 12 <= len(d) <= 19 and pii.luhn(d):
            out.append((m.start(), 2, "card", m.end()))
    out += [(m.start(), 3, "phone", m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 9 <= len(re.sub("[^0-9]", "", m.group())) <= 15]
    return [(s, e, k) for s, _, k, e in sorted(out)]


@settings(max_examples=300, deadline=None)
@given(st.text(alphabet="a1@.+-( )2é4", max_size=40))
def test_base_spans_are_those_of_the_patterns(text):
    assert pii.base_spans(text) == slow_spans(text)


def test_adversarial_texts_end():
    for t in ("a" * 50_000 + "@" + "b" * 50_000, "1" * 100_000, "1." * 50_000, "+1(" * 30_000, "@" * 50_000):
        pii.base_spans(t)
        pii.candidates(t)


def test_personal_data(spark, sf, odd, none, docs):
    texts = {r.doc_id: r.text for r in docs.collect()}
    for r in Q.op8_weak_supervision_pii(spark, sf).collect():
        want = slow_spans(texts[r.doc_id])
        assert r.base_sha256 == hashlib.sha256(pii.written_out(want).encode()).hexdigest()
        assert {f"{k}:{s}:{e}" for s, e, k in want} <= set(r.spans.split(",")) | {""}
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(sum(k == x for *_, k in want) for x in pii.BASE)
    got = pii.find(odd).collect()
    assert len(got) == odd.count() and pii.find(none).count() == 0


def test_weak_supervision_adds_and_separates(spark):
    rows, n = [], 0
    for i in range(60):
        rows.append((n, f'please mail to user{i} at host{i} dot com or set password = "s3cr3t{i:04d}xyz" now'))
        rows.append((n + 1, f"call 415-555-{1000 + i} today; order number 000-{i:02d}-0000 shipped, see version 111-222-{3333 + i}"))
        n += 2
    rows.append((n, "plain prose about nothing at all, at home, at sea"))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r for r in pii.find(df).collect()}
    assert "email:" in got[0].spans and "secret:" in got[0].spans and "phone:" in got[1].spans
    assert "ssn:" not in got[1].spans and got[n].spans == ""
    found, _ = pii.train(pii.propose(df))
    assert set(found.prior) >= {"email", "phone", "secret", "ssn"}
    assert found.posterior("ssn", "1 -1 0 -1 0 0 1") < 0.5


def test_candidates_need_no_gate_and_secrets_no_end():
    for t in ("john (AT) example (DOT) com", "john AT example DOT com", "john at example.com", "john at example.com or else (at) noon"):
        assert (0, len(t.split(" or ")[0]), "email") in pii.candidates(t)
    t = "api_key=" + "k3Y" * 100
    assert pii.candidates(t) == [(8, 308, "secret")]


@settings(max_examples=300, deadline=None)
@given(st.lists(st.sampled_from(["a", "at", "AT", " ", "(at)", "@", ".", "dot", " dot ", "com", "foo", ",", "b" * 40]), max_size=40).map("".join))
def test_spelt_addresses_are_those_of_the_pattern(text):
    assert pii.spelt(text) == [m.span() for m in pii._SPELT.finditer(text)]


# -- the methods' decisions by brute force -------------------------------------------------------


def test_out_of_place_distance_is_that_of_the_brute_force(spark, docs):
    profiles = langid.learn(docs.filter("lang IS NOT NULL"), per_lang=50)
    ranked = {}
    for i, lang in enumerate(profiles.langs):
        at = profiles.ranks[i, :-1]
        ranked[lang] = [int(g) for g in profiles.union[np.argsort(np.where(at < 0, 10**9, at), kind="stable")[: (at >= 0).sum()]]]
    texts = [r.text for r in docs.limit(40).collect()]
    for t in texts:
        best = langid.top(*langid.grams(t), langid.PROFILE).tolist()
        got = profiles.predict(t)
        if not best:
            assert got == ("und", 0.0)
            continue
        away = {x: sum(abs(r.index(g) - i) if g in r else langid.PROFILE for i, g in enumerate(best)) for x, r in ranked.items()}
        want = min(away, key=lambda x: (away[x], x))
        assert got == (want, pytest.approx(1 - away[want] / (langid.PROFILE * len(best))))


def test_machine_margin_over_real_features_is_the_pair_sum(docs):
    f, m = quality.Features(n_meta=1), quality.Machine(quality.Features(n_meta=1).size)
    m.w[:] = np.random.default_rng(1).normal(0, 0.1, len(m.w))
    m.v[:] = np.random.default_rng(2).normal(0, 0.1, m.v.shape)
    for r in docs.select("text", "n_chars").limit(6).collect():
        words = " ".join((r.text or "").split()[:60])
        idx, val = f(words, (r.n_chars,))
        pairs = sum(float(m.v[idx[i]] @ m.v[idx[j]]) * val[i] * val[j] for i in range(len(idx)) for j in range(i))
        assert m.margin(idx, val) == pytest.approx(m.w0 + float(m.w[idx] @ val) + pairs, abs=1e-3)
    a, b = f("same words", (10,)), f("same words", (None,))
    assert a[0].tolist() != b[0].tolist()  # metadata is a feature, null a bucket of its own


def test_repeated_ids_do_not_swell_the_training_sample(spark, docs):
    labels = spark.createDataFrame([(1, 0), (2, 1)], "doc_id long, quality int")
    from pyspark.sql import functions as F

    many = spark.range(3000).select(F.lit(1).cast("long").alias("doc_id"), F.concat(F.lit("text "), F.col("id")).alias("text")).union(spark.createDataFrame([(2, "other words")], "doc_id long, text string"))
    m = quality.learn(many, labels, sample=50)
    assert quality.score(many, m).count() == 3001


def slow_fingerprint(text):
    import xxhash

    words = re.findall("[^\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m.group().lower(), text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    hashes = [xxhash.xxh64_intdigest(x.encode(), 42) for x in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_fingerprints_are_those_of_the_brute_force(docs, odd):
    from fieldpress.llm import simhash

    texts = [r.text for r in docs.limit(60).collect()] + [r.text for r in odd.collect()] + ["A b", "É é\x0bX\u00a0y Z z", "one", " \t"]
    for t in texts:
        if t is None or len(t) < 60_000:
            assert simhash.fingerprint(t) == slow_fingerprint(t)


def test_reliabilities_are_those_of_the_brute_force():
    """The same expectation-maximisation candidate by candidate in place of counts of patterns."""
    rng = np.random.default_rng(0)
    rows = []
    for _ in range(400):
        y = rng.random() < 0.4
        rows.append(("email" if rng.random() < 0.7 else "phone", tuple(int(rng.choice([1, 0, -1], p=[0.6, 0.3, 0.1] if y else [0.1, 0.3, 0.6])) for _ in range(pii.LABELERS))))
    counts = {}
    for k, v in rows:
        counts[k, " ".join(map(str, v))] = counts.get((k, " ".join(map(str, v))), 0) + 1
    got = pii.Reliability().fit([(k, v, n) for (k, v), n in sorted(counts.items())], rounds=20)
    post = [1 / (1 + np.exp(-sum(v))) for _, v in rows]
    for _ in range(20):
        table = np.zeros((2, pii.LABELERS, 3)) + np.array([[[2.0, 1.0, 0.5]], [[0.5, 1.0, 2.0]]])
        for (_, v), p in zip(rows, post):
            for i, x in enumerate(v):
                table[0, i, x + 1] += 1 - p
                table[1, i, x + 1] += p
        table /= table.sum(axis=2, keepdims=True)
        prior = {k: (sum(p for (q, _), p in zip(rows, post) if q == k) + 1) / (sum(q == k for q, _ in rows) + 2) for k in ("email", "phone")}
        odds = [np.log(prior[k] / (1 - prior[k])) + sum(np.log(table[1, i, x + 1] / table[0, i, x + 1]) for i, x in enumerate(v)) for k, v in rows]
        post = [1 / (1 + np.exp(-o)) for o in odds]
    assert np.abs(got.table - table).max() < 1e-9 and all(got.prior[k] == pytest.approx(prior[k]) for k in prior)


@settings(max_examples=300, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 40), st.integers(1, 12)), max_size=12), st.lists(st.tuples(st.integers(0, 40), st.integers(1, 12)), max_size=8))
def test_free_spans_are_those_of_the_brute_force(cands, spans):
    cands = sorted({(s, s + n, "person") for s, n in cands}, key=lambda x: (x[0], -x[1]))
    spans = [(s, s + n, "ip") for s, n in spans]
    want, end = [], -1
    for s, e, k in cands:
        if s >= end and not any(a < e and s < b for a, b, _ in spans):
            want.append((s, e, k))
            end = e
    assert pii.free(cands, spans) == want


def test_recall_of_added_spans_on_planted_data(spark):
    """Written-out addresses, national numbers and secrets among look-alikes: found, and few look-alikes added."""
    rng = np.random.default_rng(7)
    rows, planted = [], 0
    for i in range(300):
        kind = i % 6
        word = "".join(rng.choice(list("abcdefghijklmnop"), 6))
        text = ["Please write to {w} at {w}mail dot com for details.", "Call 415-555-{n} by phone today.", "The password = \"{w}X9{n}zz\" is set.", "Figure 123-456-{n} in table version of the order.", "We stayed at {w} dot and then left for home.", "Plain words about {w} and nothing else."][kind].format(w=word, n=1000 + i)
        rows.append((i, text))
        planted += kind < 3
    got = {r.doc_id: r.n_added for r in pii.find(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    found = sum(got[i] > 0 for i in got if i % 6 < 3)
    wrong = sum(got[i] > 0 for i in got if i % 6 >= 4)
    assert found >= 0.9 * planted and wrong <= 0.05 * 100


def test_planted_junk_is_rejected_and_prose_kept(spark, docs):
    """Symbol soup, bytes without pieces and one repeated token pass the base rule, and fail the bands of their language."""
    rng = np.random.default_rng(2)
    soup = " ".join("".join(rng.choice(list("#%&@^~+=/\\"), 9)) for _ in range(80))
    fallback = " ".join("".join(chr(int(c)) for c in rng.integers(0x12000, 0x12400, 4)) for _ in range(80))
    letters = " ".join("".join(rng.choice(list("bcdfghjklmnpqrstvwxz"), 8)) for _ in range(80))
    measured_rows = docs.select("doc_id", "text", "lang").unionByName(spark.createDataFrame([(10**6 + i, t, "en") for i, t in enumerate((soup, fallback, letters))], "doc_id long, text string, lang string"))
    rows = fertility.judge_fitted(fertility.measure(measured_rows, P.path("piece_bpe_32k.model"), lang_col="lang")).collect()
    junk = {r.doc_id: r for r in rows if r.doc_id >= 10**6}
    assert all(not r.base_failed and not r.kept for r in junk.values())
    rest = [r for r in rows if r.doc_id < 10**6 and not r.base_failed]
    assert np.mean([r.kept for r in rest]) > 0.8
