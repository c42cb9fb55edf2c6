"""Operators over the whole corpus: licences, hosts, near-duplicates, lines, decontamination, pipeline."""

import re

import numpy as np
import public_tokenizers as P
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

import corpus_pipeline
from fieldpress.llm import bpe, contamination, hosts, licences, lines, simhash
from fieldpress.llm import queries as Q

from tests.llm.conftest import PROSE


@pytest.mark.parametrize("name", sorted(Q.SQL))
def test_queries_match_their_sql(spark, sf, duck, name):
    df = Q.QUERIES[name](spark, sf)
    o = duck.execute(Q.SQL[name])
    names = [d[0] for d in o.description]
    assert sorted(names) == sorted(df.columns)
    a = sorted((tuple(str(r[c]) for c in names) for r in df.collect()))
    assert a == sorted(tuple(map(str, r)) for r in o.fetchall())


# -- op2 -------------------------------------------------------------------------------------


def test_licences(spark, odd, none):
    rows = [
        (1, "Some prose first.\nReleased under the MIT License.\nMore prose."),
        (2, "Released under the terms of the MIT License today, said nobody in a longer sentence about software."),
        (3, "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version"),
        (4, "Licensed under the\nApache License,\nVersion 2.0."),
        (5, None),
    ]
    got = {r.doc_id: r for r in licences.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[1].licence == "MIT" and got[1].dice == 1000
    assert got[2].licence is None and got[5].licence is None and got[5].dice == 0
    assert got[3].licence == "GPL-3.0-header" and got[4].licence == "Apache-2.0"
    assert licences.scan(odd).count() == odd.count() and licences.scan(none).count() == 0
    assert licences.scan(odd, {}).where("licence IS NOT NULL").count() == 0
    many = {str(i): f"alpha{i} beta{i} gamma{i}" for i in range(1200)}
    got = licences.scan(spark.createDataFrame([(1, "so alpha777 beta777 gamma777"), (2, "alpha3 beta4 gamma5")], "doc_id long, text string"), many).collect()
    assert {r.doc_id: r.licence for r in got} == {1: "777", 2: None}


def dice(a, b):
    a, b = set(licences.template_bigrams(a)), set(licences.template_bigrams(b))
    return 2 * len(a & b) / (len(a) + len(b)) if a or b else 0.0


def test_whole_texts_comments_and_notices_inside_lines(spark):
    t = licences.TEMPLATES
    bsd = "/*\n * " + t["BSD-3-Clause-text"].replace("\n\n", "\n *\n * ") + "\n */\nint main() {}"
    rows = [
        (1, "MIT License\n\nCopyright (c) 2020 somebody\n\n" + t["MIT-text"].replace(", ", ",\n") + "\n\nThen code."),
        (2, bsd),
        (3, "Words come first. " + t["GPL-3.0-header"] + " Words come after it, all in one line."),
        (4, "word " * 40 + "\n" + t["ISC-text"] + "\n" + "word " * 40),
    ]
    got = {r.doc_id: r for r in licences.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [got[i].licence for i in (1, 2, 3, 4)] == ["MIT-text", "BSD-3-Clause-text", "GPL-3.0-header", "ISC-text"]
    assert all(got[i].dice == 1000 for i in (1, 2, 3, 4))


def test_dice_is_that_of_the_brute_force(spark):
    """A unit that is the whole text: the best template by comparing with all."""
    rng = np.random.default_rng(5)
    rows = []
    for i, (name, text) in enumerate(sorted(licences.TEMPLATES.items())):
        words = [w for w in text.replace("\n", " ").split() if rng.random() > 0.04]
        rows.append((i, " ".join(w.strip(".!?") for w in words)))
    got = {r.doc_id: r for r in licences.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for i, text in rows:
        best = min((-int(1000 * dice(text, t) + 1e-9), -len(licences.template_bigrams(t)), n) for n, t in licences.TEMPLATES.items())
        if -best[0] >= 800:
            assert (got[i].licence, got[i].dice) == (best[2], -best[0])
        else:
            assert got[i].licence is None


def test_paragraphs_of_licence_texts(spark):
    rows = []
    for i, kind in enumerate(("MIT", "ISC", "BSD")):
        parts = [t for n, t in licences.TEMPLATES.items() if n in (f"{kind}-grant", f"{kind}-notice", f"{kind}-warranty", f"{kind}-intro", f"{kind}-disclaimer") or n.startswith(f"{kind}-clause-")]
        wrapped = ["\n".join(" ".join(t.split()[j : j + 9]) for j in range(0, len(t.split()), 9)) for t in parts]
        rows.append((i, "Copyright (c) somebody\n\n" + "\n\n".join(wrapped), len(parts)))
    for r, (_, _, n), kind in zip(licences.scan(spark.createDataFrame(rows, "doc_id long, text string, n long")).orderBy("doc_id").collect(), rows, ("MIT", "ISC", "BSD")):
        assert r.licence.startswith(kind) and r.dice == 1000 and r.n_units >= n >= 2


@settings(max_examples=60, deadline=None)
@given(st.sampled_from(sorted(licences.TEMPLATES)), st.lists(st.integers(0, 60), max_size=6), st.integers(0, 10**6))
def test_prefix_is_necessary(name, holes, seed):
    """Whatever reaches the threshold has a prefix word."""
    grams = licences.template_bigrams(licences.TEMPLATES[name])
    rng = np.random.default_rng(seed)
    unit = {g for i, g in enumerate(grams) if i not in holes} | {f"x{j} y{j}" for j in range(int(rng.integers(0, 5)))}
    inter = len(unit & set(grams))
    if 2 * inter >= 0.8 * (len(unit) + len(grams)):
        words = {w for g in unit for w in g.split()}
        assert words & licences.prefix_words(grams, 0.8)


# -- op5 -------------------------------------------------------------------------------------


def test_hosts_and_rules(spark):
    urls = ["https://WWW.Example.com/en/x?y", "http://a.example.com/en/", "http://example.com/fr", "http://x.net/es/1", "ftp://h.org#f", None, "nothing", "http://badexample.com/en/", "http://com/", "http://h.net"]
    pages = spark.createDataFrame([(i, u) for i, u in enumerate(urls)], "page_id long, url string")
    outcomes = spark.createDataFrame([("h.org", 9, 10), ("x.net", 0, 5)], "host string, bad long, n long")
    r = {x.page_id: x for x in hosts.judge(pages, outcomes, Q.URL_RULES).collect()}
    assert (r[0].host, r[0].path, r[0].rule, r[0].verdict) == ("www.example.com", "/en/x", "www.example.com/en/", "allow")
    assert (r[1].rule, r[1].verdict) == ("example.com/en/", "block") and r[2].rule == "com/"
    assert (r[3].rule, r[3].verdict) == ("net/es/", "block") and r[7].rule == "com/" and r[8].rule == "com/"
    assert (r[5].host, r[5].path, r[5].rule) == ("", "", None) == (r[6].host, r[6].path, r[6].rule)
    assert r[4].host == "h.org" and r[9].path == "" and r[9].rule is None
    none = hosts.judge(pages, outcomes.where("false"), Q.URL_RULES)
    assert none.count() == len(urls) and none.where("rule IS NULL AND verdict <> 'allow'").count() == 0
    assert hosts.judge(pages.where("false"), outcomes, []).count() == 0


def test_shrinkage(spark):
    rows = [("a.big.com", 90, 100), ("b.big.com", 1, 1), ("c.big.com", 0, 1), ("x.good.com", 0, 200), ("y.good.com", 2, 100), ("z.other.org", 1, 50), ("w.fourth.org", 3, 60)]
    pages = spark.createDataFrame([("new.big.com",), ("new.good.com",), ("new.org",)], "host string")
    got = {r.host: r for r in hosts.reputation(spark.createDataFrame(rows, "host string, bad long, n long"), pages).collect()}
    assert got["a.big.com"].blocked and got["a.big.com"].tail < 0.001 and not got["x.good.com"].blocked
    # one bad page does not damn a host, and a host borrows from its domain, also without a page of its own
    assert got["c.big.com"].share > got["x.good.com"].share and got["b.big.com"].share < 1
    assert got["new.big.com"].share > got["new.good.com"].share and len(got) == 10
    assert all(0 <= r.share <= 1 and 0 <= r.tail <= 1 and r.blocked == (r.tail < hosts.RISK) for r in got.values())


def test_hosts_far_over_the_overall_share_are_blocked(spark):
    rows = [("bad.com", 120, 400), *((f"good{i}.com", i, 200) for i in range(12)), ("one.com", 1, 1)]
    pages = spark.createDataFrame([(i, f"http://{h}/") for i, (h, *_) in enumerate(rows)], "page_id long, url string")
    got = {r.host: r for r in hosts.judge(pages, spark.createDataFrame(rows, "host string, bad long, n long"), []).collect()}
    assert got["bad.com"].verdict == "block" and got["bad.com"].share < 0.5
    assert all(r.verdict == "allow" for h, r in got.items() if h != "bad.com")


def test_beta_tail_is_the_integral(spark):
    """Against the trapezoid rule over the density (in a variable that removes its poles) and exact binomial sums."""
    from math import comb

    from pyspark.sql import functions as F

    cases = [(x, a, b) for x in (0.05, 0.2, 0.7) for a, b in ((0.3, 2.5), (1.0, 1.0), (3.4, 17.0), (40.5, 200.0), (900.0, 9000.0))]
    for x in (0.05, 0.2, 0.7):
        some = [(a, b) for y, a, b in cases if y == x]
        got = [r.t for r in spark.createDataFrame(some, "a double, b double").coalesce(1).select(hosts.beta_tail(x, F.col("a"), F.col("b")).alias("t")).collect()]
        for (a, b), t in zip(some, got):
            z = np.linspace(0, 1, 2_000_001)[1:-1]
            s = z**2 * (3 - 2 * z)  # flat at both ends
            f = np.exp((a - 1) * np.log(s) + (b - 1) * np.log1p(-s) - (a * np.log(a / (a + b)) + b * np.log(b / (a + b)))) * 6 * z * (1 - z)
            assert abs(t - f[s <= x].sum() / f.sum()) < 2e-4, (x, a, b)
    n, k = 30, 4  # whole numbers: the tail is a binomial sum
    got = spark.range(1).select(hosts.beta_tail(0.2, F.lit(float(k)), F.lit(float(n - k + 1))).alias("t")).first().t
    assert abs(got - sum(comb(n, i) * 0.2**i * 0.8 ** (n - i) for i in range(k, n + 1))) < 1e-11


def test_the_method_blocks_and_odd_pages(spark):
    text = "<p>" + "plain words of a page " * 5 + "</p>"
    rows = [(i, f"https://www.casino-win.example.net/p{i}", text) for i in range(30)]
    rows += [(100 + i, f"https://site{i % 9}.example.net/p{i}?q=1", text) for i in range(200)]
    rows += [(900, None, None), (901, "no scheme", text), (902, "https://site1.example.net/", None), (902, "https://site1.example.net/", None)]
    pages = spark.createDataFrame([(*r, 1.0, "x", "y") for r in rows], "page_id long, url string, html string, share double, host string, k string")
    got = hosts.judge(pages, hosts.count_outcomes(pages), []).collect()
    assert len(got) == len(rows)
    assert {r.verdict for r in got if r.host == "www.casino-win.example.net"} == {"block"}
    assert {r.verdict for r in got if r.host != "www.casino-win.example.net"} == {"allow"}
    assert sum(r.page_id == 902 for r in got) == 2 and {r.host for r in got if r.page_id in (900, 901)} == {""}


def test_many_rules_are_joined(spark):
    rules = [("block", f"h{i}.com/") for i in range(40)] + [("allow", "h3.com/en/"), ("allow", "com/"), ("block", "com/x")]
    urls = ["http://a.h3.com/en/x", "http://h3.com/fr", "http://h50.com/y", "http://h50.com/xyz", "http://org/", None]
    pages = spark.createDataFrame([(i, u) for i, u in enumerate(urls)], "page_id long, url string")
    none = spark.createDataFrame([], "host string, bad long, n long")
    few, many = (sorted((r.page_id, r.rule, r.verdict) for r in hosts.judge(pages, none, rules, literal_rules=n).collect()) for n in (500, 1))
    assert few == many == [(0, "h3.com/en/", "allow"), (1, "h3.com/", "block"), (2, "com/", "allow"), (3, "com/x", "block"), (4, None, "allow"), (5, None, "allow")]


def test_domains(spark):
    from pyspark.sql import functions as F

    df = spark.createDataFrame([(h,) for h in ("a.b.co.uk", "b.co.uk", "x.y.com", "com", "", "h.example.net:80")], "h string")
    got = {r.h: (r.d, r.s) for r in df.select("h", hosts.domain_of(F.col("h")).alias("d"), hosts.suffix_of(F.col("h")).alias("s")).collect()}
    assert got["a.b.co.uk"] == ("b.co.uk", "co.uk") == got["b.co.uk"] and got["x.y.com"] == ("y.com", "com")
    assert got["com"] == ("com", "com") and got[""] == ("", "") and got["h.example.net:80"] == ("example.net", "net")


# -- op7 -------------------------------------------------------------------------------------


def brute_components(fps, ids, radius=3):
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(fps):
        for j in np.flatnonzero(np.bitwise_count(fps ^ a) <= radius):
            x, y = find(ids[i]), find(ids[j])
            if x != y:
                root[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def near_copies(seed=0, n=400):
    rng = np.random.default_rng(seed)
    centres = rng.integers(0, 2**63, 12).astype(np.uint64)
    out = [int(c) for c in centres]
    while len(out) < n:
        f = int(out[rng.integers(len(out))]) if rng.random() < 0.5 else int(centres[0])
        for b in rng.integers(0, 64, rng.integers(0, 5)):
            f ^= 1 << int(b)
        out.append(f)
    return np.array(out, np.uint64)


@pytest.mark.parametrize("bucket", [2048, 8])
def test_components_are_those_of_the_brute_force(spark, bucket):
    fps = near_copies()
    ids = list(range(len(fps)))
    distinct = {int(f) for f in fps}
    prints = spark.createDataFrame([(int(np.uint64(f).astype(np.int64)),) for f in distinct], "fp long")
    label = {r.node: r.label for r in simhash.components(simhash.links(prints, bucket=bucket)).collect()}
    want = brute_components(fps, ids)
    for i in ids:
        for j in ids[:40]:
            a, b = (int(fps[x].astype(np.int64)) for x in (i, j))
            assert (label.get(a, a) == label.get(b, b)) == (want[i] == want[j])


@settings(max_examples=40, deadline=None)
@given(st.integers(0, 10_000), st.integers(1, 200), st.sampled_from([0, 1, 2, 3, 5, 7]))
def test_bit_slices_count_right(seed, n, radius):
    rng = np.random.default_rng(seed)
    fps = np.unique(near_copies(seed, n))
    block = simhash.planes(fps)
    got = np.unpackbits(simhash.near_rows(fps, block, radius).view(np.uint8), axis=1, bitorder="little")[:, : len(fps)]
    assert (got.astype(bool) == (np.bitwise_count(fps[:, None] ^ fps[None, :]) <= radius)).all()
    i, j = rng.integers(0, len(fps), 50), rng.integers(0, len(fps), 50)
    assert (simhash.near_pairs(fps[i], fps[j], radius) == (np.bitwise_count(fps[i] ^ fps[j]) <= radius)).all()


def test_near_duplicates(spark, sf, docs, odd, none):
    rows = Q.op7_simhash(spark, sf).collect()
    fps, ids = np.array([int(r.fingerprint, 16) for r in rows], np.uint64), [r.doc_id for r in rows]
    assert {r.doc_id: r.component_id for r in rows} == brute_components(fps, ids)
    got = {r.doc_id: r for r in simhash.near_duplicates(odd).collect()}
    assert got[1].fingerprint == got[3].fingerprint == "0" * 16 and got[3].component_id == 1
    assert got[5].component_id == 4 and simhash.near_duplicates(none).count() == 0
    kept = simhash.keep_one(odd)
    assert kept.columns == odd.columns and {r.doc_id for r in kept.collect()} & {1, 2, 3} == {1} and kept.where("doc_id = 5").count() == 0
    assert kept.where("doc_id IS NULL").count() == 1


# -- op9 -------------------------------------------------------------------------------------


def test_lines(spark, odd, none):
    p = "One fine sentence about rivers and hills. Another one about mills and stones. A third about boats and nets.\n"
    rows = [(1, "Alpha start here. " + p + "Own ending of one."), (2, "Other start there.\n" + p + "Own ending\x01of two\x02."), (3, p), (4, "short.\nlines"), (5, None), (6, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.text for r in lines.remove_repeats(df).collect()}
    assert got[1] == rows[0][1] and got[2] == "Other start there.\nOwn ending\x01of two\x02." and got[3] == "" and got[4] == rows[3][1] and got[5] is None and got[6] == ""
    out = lines.remove_repeats(odd, counts=("n_lines", "n_removed"))
    assert out.columns == [*odd.columns, "n_lines", "n_removed"] and out.count() == odd.count()
    back = {r.doc_id: r for r in out.collect()}
    texts = {r.doc_id: r.text for r in odd.collect()}
    assert back[7].text == texts[7] and back[1].text is None and back[None].text == texts[None]
    six = texts[9].split("\n")
    assert back[9].text and len(back[9].text.split("\n")) < len(six)  # its own lines repeat
    assert back[4].text and PROSE.startswith(back[4].text.rstrip()[:60]) and len(back[4].text) < len(texts[4]) and back[5].text == ""  # doc 4 repeats its own sentences, doc 5 is its copy
    assert lines.remove_repeats(none).count() == 0


def test_short_lines_are_windows_too(spark):
    verse = "".join(f"w{i} w{i + 1} w{i + 2} w{i + 3}\n" for i in range(0, 60, 4))  # 60 words in lines of 4
    rows = [(1, verse), (2, "Own first.\n" + verse + "Own last."), (3, "\n\n\n\nend of three"), (4, "\n\n\n\nend of four")]
    got = {r.doc_id: r.text for r in lines.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[1] == verse and got[2] == "Own first.\nOwn last." and got[3] == rows[2][1] and got[4] == rows[3][1]


def slow_lines(text, prose=True):
    """The cutting rule word by word."""
    out = []
    while text:
        words = re.findall(r"[^ \n]*[ \n]", text)[: lines.MOST]  # the last piece has no separator and ends nothing
        words = words[: next((i + 1 for i, w in enumerate(words) if w.endswith("\n")), len(words))]
        n = 0
        if prose:
            ends = lambda w, marks: w.endswith("\n") or w[:-1][-1:] in marks and len(w) > 1
            first = [i + 1 for i, w in enumerate(words[: lines.LEAST - 1]) if ends(w, tuple(".!?"))]
            later = [[i + 1 for i, w in enumerate(words) if i + 1 >= lines.LEAST and (ends(w, tuple(m)) if m[0] == "." else len(w) > 1 and w[-1] == " " and w[-2] in m)] for m in (".!?,;:", *lines.ENDS)]
            n = next((x[0] for x in [first, *later] if x), lines.MOST if len(words) == lines.MOST and not words[-1].endswith("\n") else 0)
            cut = "".join(words[:n])
        if not n:
            cut = text[: text.index("\n")] if "\n" in text else text
            cut = cut + "\n" if not prose and "\n" in text else cut
        out.append(cut)
        text = text[len(cut) :]
    return out


@settings(max_examples=300, deadline=None)
@given(st.text(alphabet="adtk.,!    \n", max_size=160), st.booleans())
def test_lines_are_those_of_the_rule(text, prose):
    want = slow_lines(text, prose)
    assert "".join(want) == text
    for pattern in (lines.PROSE, lines.PROSE_JAVA) if prose else (lines.PLAIN,):
        assert re.findall(pattern, text) == want


def slow_removal(rows, prose=True):
    """rows: (id, text), one an id. Texts after removal, by a dictionary of windows."""
    seen, out = set(), {}
    for i, text in sorted(rows):
        cut = slow_lines(text, prose)
        bare = [x.strip(" \n") for x in cut]
        gone = set()
        for p in range(len(cut) - 2):
            w = tuple(bare[p : p + 3])
            if any(w):
                if w in seen:
                    gone |= {p, p + 1, p + 2}
                seen.add(w)
        out[i] = "".join(x for p, x in enumerate(cut) if p not in gone)
    return out


@pytest.mark.parametrize("key", ["long", "string"])
def test_removal_is_that_of_the_brute_force(spark, docs, key):
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
    if key == "string":
        rows = [(f"d{i:05d}", t) for i, t in rows]
    got = {r.doc_id: r.text for r in lines.remove_repeats(spark.createDataFrame(rows, f"doc_id {key}, text string"), broadcast_bytes=0 if key == "string" else 10**7).collect()}
    assert got == slow_removal(rows)


def test_passages_in_long_lines_go(spark):
    """60 words without a sentence end, glued to other text at both ends, in one line."""
    rng = np.random.default_rng(3)
    word = lambda: "".join(rng.choice(list("abcdefghijklmnoprstuvwy"), rng.integers(2, 9)))
    passage = " ".join(word() for _ in range(60))
    rows = [(i, " ".join([*(word() for _ in range(int(rng.integers(5, 30)))), passage, *(word() for _ in range(int(rng.integers(5, 30))))])) for i in range(40)]
    got = {r.doc_id: r.text for r in lines.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    left = passage.split()
    assert got[0] == rows[0][1]
    for i in range(1, 40):
        runs = sum(" ".join(left[j : j + 50]) in got[i] for j in range(11))
        assert runs == 0
        assert len(got[i].split()) >= len(rows[i][1].split()) - 60


# -- op10 ------------------------------------------------------------------------------------


def test_contamination(spark, odd, none):
    item = "one two three four five six seven eight nine ten eleven twelve thirteen fourteen"
    items = spark.createDataFrame([(1, item), (10, "tiny item"), (2, None), (3, "..."), (4, item.upper())], "item_id long, text string")
    rows = [(1, "x " + item + " y"), (2, "One, TWO three: four five six seven eight nine ten eleven twelve thirteen!"), (3, "a tiny item " + "word " * 50), (4, "tiny. items"), (5, None), (5, None), (6, "É é tiny É item")]
    got = {r.doc_id: r for r in contamination.contaminated(spark.createDataFrame(rows, "doc_id long, text string"), items).collect()}
    assert (got[1].n_words, got[1].n_hit, got[1].items, got[1].contaminated) == (16, 14, ["1", "4"], True)
    assert (got[2].n_hit, got[2].items) == (13, ["1", "4"])
    assert (got[3].n_hit, got[3].n_words, got[3].contaminated) == (2, 53, False)
    assert got[4].n_hit == 0 and got[5].n_words == 0 and not got[5].contaminated and got[6].n_hit == 0
    far = contamination.contaminated(spark.createDataFrame(rows, "doc_id long, text string"), items, broadcast_bytes=0)
    assert sorted(map(str, far.collect())) == sorted(map(str, contamination.contaminated(spark.createDataFrame(rows, "doc_id long, text string"), items).collect())) and far.count() == len(rows)
    assert contamination.contaminated(none, items).count() == 0
    assert contamination.contaminated(odd, items.where("false")).where("n_hit > 0").count() == 0
    more = [("99L", item), ("99L", item), ("99L", "clean words of the same id"), ("CAST(NULL AS BIGINT)", item), ("4L", item)]
    both = odd
    for i, text in more:
        both = both.unionByName(odd.limit(1).selectExpr(f"{i} doc_id", f"'{text}' text", "lang", "score", "fp", "tid", "k1", "covered", "quality_score", "words"))
    kept = contamination.drop_contaminated(both, items)
    assert kept.columns == odd.columns and kept.count() == odd.count() + 1
    assert [r.text for r in kept.where("doc_id = 99").collect()] == ["clean words of the same id"] and kept.where("doc_id = 4").count() == 1 and kept.where("doc_id IS NULL").count() == 1
    assert contamination.contaminated(both, items).count() == both.count()
    named = spark.createDataFrame([("a", item), ("a", item), (None, "x")], "doc_id string, text string")
    assert sorted((str(r.doc_id), r.contaminated) for r in contamination.contaminated(named, items).collect()) == [("None", False), ("a", True), ("a", True)]


# -- pipeline --------------------------------------------------------------------------------


def test_pipeline(spark, sf, docs):
    out = {r.doc_id: r for r in corpus_pipeline.run(spark, sf).collect()}
    step = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        step = stage(spark, step, sf)
        assert step.columns == docs.columns, name
    last = {r.doc_id: r.text for r in step.collect()}
    assert out.keys() == last.keys() and 0 < len(out) < docs.count()
    coder = bpe.Coder(P.path("byte_bpe_50k.tiktoken"), P.PATTERN)
    for i, text in last.items():
        assert coder.decode(np.array(out[i].token_ids, np.uint32).tobytes()).decode() == text


def test_native_operators_run_no_python(spark, sf):
    for name in ("op2_licence_dice", "op9_line_windows", "op10_prefix_decontamination"):
        plan = Q.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
        assert "Python" not in plan and "Arrow" not in plan and "Pandas" not in plan and "Cartesian" not in plan
