"""Personal data by weak supervision.

Base patterns (email, ip, card, phone) always count. Wider generators propose further
candidates (written-out addresses, national phone numbers, account numbers, secrets,
titled names). Seven labelers - shape, checksum, context words for and against, gazetteer,
variety of characters, boundaries - vote for, against or not. Expectation-maximisation over the
counts of vote patterns (all candidates; at most kinds x 3^7 rows reach the driver)
estimates each labeler's reliability; its posteriors train a logistic span classifier on
hashed features of about ``SAMPLE`` candidates at most. Candidates the classifier accepts, and
that overlap no base span, are added.

One pass over the texts; candidates are written once without the texts, then scored. No
shuffle but the pattern counts.

Defined cases: null text is empty; the base patterns' failing matches are dropped without
a retry inside them; equal starts are ordered by kind; of overlapping accepted candidates
the first, then the longer, stays; with no candidate in the corpus only base spans are returned.
"""

from __future__ import annotations

import hashlib
import math
import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import map_batches, written

SAMPLE = 8000
BITS = 12
ACCEPT = 0.5
LABELERS = 7
BASE = ("email", "ip", "card", "phone")
KINDS = (*BASE, "iban", "person", "secret", "ssn")
_ORDER = {k: i for i, k in enumerate(KINDS)}

# The base patterns.
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        v = int(c)
        if i & 1:
            v = 2 * v - 9 * (v > 4)
        total += v
    return total % 10 == 0


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost matches of local part, @ and domain. All starts of one local run share its @, so each @ is tried once."""
    out, end, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > end and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at + 1) if start < at else None
        if m:
            end = m.end()
            out.append((start, end))
        at = text.find("@", max(at + 1, end))
    return out


def ips(text: str) -> list[tuple[int, int]]:
    """The leftmost start of a match is always the start of a run of digits, or just after the match before."""
    out, pos = [], 0
    while m := _IP.search(text, pos):
        if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m.group().split(".")):
            out.append(m.span())
        pos = m.end()
    return out


def base_spans(text: str) -> list[tuple[int, int, str]]:
    found = [(s, e, "email") for s, e in emails(text)]
    found += [(s, e, "ip") for s, e in ips(text)]
    for m in _CARD.finditer(text):
        digits = m.group().replace(" ", "").replace("-", "")
        if 12 <= len(digits) <= 19 and luhn(digits):
            found.append((*m.span(), "card"))
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 9 <= sum(c in "0123456789" for c in m.group()) <= 15:
                found.append((*m.span(), "phone"))
    return sorted(found, key=lambda x: (x[0], _ORDER[x[2]]))


def written_out(spans) -> str:
    return ",".join(f"{k}:{s}:{e}" for s, e, k in spans)


# -- candidates --------------------------------------------------------------------------

_SPELT = re.compile(r"\b[A-Za-z0-9._%+-]{1,64}\s?(?:\(at\)|\[at\]|\{at\}|\bat\b|@)\s?[A-Za-z0-9-]{1,63}(?:\s?(?:\(dot\)|\[dot\]|\{dot\}|\bdot\b|\.)\s?[A-Za-z0-9-]{2,63}){1,4}", re.I)
#: What every match of _SPELT has in it, at most 65 characters behind its start.
_AT = re.compile(r"\bat\b|@", re.I)
_NATIONAL = re.compile(r"(?<![0-9+])(?:00[1-9][0-9]{0,2}[ .-])?\(?[0-9]{3}\)?[ .-][0-9]{3}[ .-][0-9]{4}(?![0-9])")
_IBAN = re.compile(r"\b[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?\b")
_SSN = re.compile(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])")
_SECRET = re.compile(r"\b(?:token|password|passwd|pwd|secret|api[_-]?key|access[_-]?key)\b\s{0,3}[=:]\s{0,3}[\"']?([A-Za-z0-9+/_=.-]{8,})", re.I)
_CLOUD_KEY = re.compile(r"\b(?:AKIA|ASIA)[0-9A-Z]{16}\b")
_PERSON = re.compile(r"\b(?:Mr|Mrs|Ms|Dr|Prof)\.?\s[A-Z][a-zà-ÿ]{1,30}(?:\s[A-Z][a-zà-ÿ]{1,30})?")
_DIGIT = re.compile(r"[0-9]")

# Gazetteers and context words.
_FOR = {
    "email": ("mail", "contact", "write", "reach", "address"),
    "phone": ("tel", "phone", "call", "fax", "mobile", "cell", "number"),
    "iban": ("iban", "account", "bank", "transfer"),
    "person": ("name", "dear", "signed", "patient", "author", "by"),
    "secret": ("token", "password", "passwd", "pwd", "secret", "key", "login"),
    "ssn": ("ssn", "social", "security", "tax"),
}
_AGAINST = ("version", "isbn", "issn", "page", "figure", "table", "chapter", "serial", "sku", "order", "invoice", "placeholder", "your_", "xxx")
_TOP_DOMAINS = frozenset("com org net edu gov mil info biz io co uk de fr es it nl eu ch at be us ca au jp".split())
_COUNTRIES = frozenset("AT BE BG CH CY CZ DE DK EE ES FI FR GB GR HR HU IE IS IT LI LT LU LV MC MT NL NO PL PT RO SE SI SK".split())


def spelt(text: str) -> list[tuple[int, int]]:
    """The matches of _SPELT, looked for only around what each has in it: a match ends within 512 characters behind that."""
    out, end = [], 0
    for at in _AT.finditer(text):
        if at.start() >= end:
            m = _SPELT.search(text, max(end, at.start() - 66), at.end() + 512)
            if m and m.start() < at.start():
                end = m.end()
                out.append(m.span())
    return out


def candidates(text: str) -> list[tuple[int, int, str]]:
    """Spans of the wider generators, in order, each once."""
    found = [(s, e, "email") for s, e in spelt(text)]
    if _DIGIT.search(text):
        found += [(*m.span(), "phone") for m in _NATIONAL.finditer(text)]
        found += [(*m.span(), "iban") for m in _IBAN.finditer(text)]
        found += [(*m.span(), "ssn") for m in _SSN.finditer(text)]
    if "=" in text or ":" in text:
        found += [(*m.span(1), "secret") for m in _SECRET.finditer(text)]
    if "AKIA" in text or "ASIA" in text:
        found += [(*m.span(), "secret") for m in _CLOUD_KEY.finditer(text)]
    if any(x in text for x in ("Mr", "Ms", "Dr", "Prof")):
        found += [(*m.span(), "person") for m in _PERSON.finditer(text)]
    return sorted(set(found), key=lambda x: (x[0], _ORDER[x[2]], -x[1]))


def _checksum(kind: str, span: str) -> int:
    if kind == "iban":
        s = span.replace(" ", "")
        return 1 if int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1 else -1
    if kind == "ssn":
        a, b, c = span.split("-")
        return -1 if a in ("000", "666") or a[0] == "9" or b == "00" or c == "0000" else 1
    if kind == "phone":
        n = sum(c.isdigit() for c in span)
        return 1 if 9 <= n <= 15 else -1
    return 0


def _gazetteer(kind: str, span: str) -> int:
    if kind == "email":
        return 1 if re.split(r"[^A-Za-z0-9]+", span.rstrip(")]}"))[-1].lower() in _TOP_DOMAINS else -1
    if kind == "iban":
        return 1 if span[:2] in _COUNTRIES else -1
    if kind == "phone":
        area = re.sub(r"\D", "", span)[-10:]
        return -1 if area[:1] in "01" else 1
    if kind == "secret":
        return 1 if span[:4] in ("AKIA", "ASIA", "ghp_", "xoxb") else 0
    return 0


def votes(text: str, start: int, end: int, kind: str) -> tuple[int, ...]:
    """The seven labelers' votes on a candidate: 1 for, -1 against, 0 none."""
    span, left, right = text[start:end], text[max(0, start - 40) : start].lower(), text[end : end + 20].lower()
    near = left + " " + right
    classes = len({"d" if c.isdigit() else "a" if c.isalpha() else "o" for c in span})
    shape = {"email": "dot" in span.lower() or "at)" in span.lower() or "at]" in span.lower(), "phone": span.count("-") + span.count(".") + span.count(" ") >= 2, "iban": len(span.replace(" ", "")) >= 15, "ssn": True, "secret": len(span) >= 12, "person": True}[kind]
    variety = len(set(span.lower())) / max(1, min(len(span), 128))
    outside = (text[start - 1 : start], text[end : end + 1])
    return (
        1 if shape else -1,
        _checksum(kind, span),
        1 if any(w in near for w in _FOR[kind]) else 0,
        -1 if any(w in near for w in _AGAINST) else 0,
        _gazetteer(kind, span),
        -1 if len(set(re.sub(r"\W", "", span))) < 3 else 1 if kind == "secret" and classes > 1 and variety > 0.2 else 0,
        -1 if any(c.isalnum() for c in outside) else 1,
    )


def features(text: str, start: int, end: int, kind: str) -> list[int]:
    """Hashed features of a span for the final classifier: kind, shape, length, affixes, neighbouring words."""
    span = text[start:end]
    shape = re.sub(r"(.)\1+", r"\1", re.sub(r"[a-zà-ÿ]", "a", re.sub(r"[A-ZÀ-Þ]", "A", re.sub(r"[0-9]", "d", span))))[:24]
    left, right = text[max(0, start - 40) : start].lower().split()[-3:], text[end : end + 40].lower().split()[:2]
    names = [kind, f"{kind}/{shape}", f"{kind}#{min(len(span), 40) // 4}", f"{kind}^{span[:2].lower()}", *(f"{kind}<{w}" for w in left), *(f"{kind}>{w}" for w in right)]
    return sorted({zlib.crc32(x.encode("utf-8", "replace")) & ((1 << BITS) - 1) for x in names})


# -- reliabilities and classifier ----------------------------------------------------------


class Reliability:
    """P(vote | class) of each labeler and a prior for each kind, by EM over pattern counts."""

    def __init__(self):
        self.table = np.zeros((2, LABELERS, 3))
        self.prior: dict[str, float] = {}

    def fit(self, patterns: list[tuple[str, str, int]], rounds: int = 60) -> "Reliability":
        if not patterns:
            return self
        kinds = sorted({k for k, _, _ in patterns})
        v = np.array([[int(x) for x in p.split(" ")] for _, p, _ in patterns])
        n = np.array([c for *_, c in patterns], float)
        k = np.array([kinds.index(x) for x, _, _ in patterns])
        score = v.sum(axis=1)
        post = 1 / (1 + np.exp(-score.astype(float)))  # starts from the majority
        one_hot = np.stack([v == -1, v == 0, v == 1], axis=2).astype(float)
        for _ in range(rounds):
            for y, w in ((0, (1 - post) * n), (1, post * n)):
                c = np.einsum("p,plv->lv", w, one_hot) + (np.array([2.0, 1.0, 0.5]) if y == 0 else np.array([0.5, 1.0, 2.0]))
                self.table[y] = c / c.sum(axis=1, keepdims=True)
            prior = np.array([((post * n)[k == i].sum() + 1) / (n[k == i].sum() + 2) for i in range(len(kinds))])
            log = np.log(self.table)
            odds = np.log(prior[k]) - np.log(1 - prior[k]) + np.einsum("plv,lv->p", one_hot, log[1] - log[0])
            post = 1 / (1 + np.exp(-np.clip(odds, -30, 30)))
        self.prior = {x: float(prior[i]) for i, x in enumerate(kinds)}
        return self

    def posterior(self, kind: str, pattern: str) -> float:
        p = self.prior.get(kind, 0.5)
        log = np.log(np.maximum(self.table, 1e-9))
        odds = math.log(p / (1 - p)) + sum(log[1, i, int(x) + 1] - log[0, i, int(x) + 1] for i, x in enumerate(pattern.split(" ")))
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, odds))))


def fit_classifier(rows: list[list[int]], target: np.ndarray, epochs: int = 20, rate: float = 0.3) -> np.ndarray:
    """Logistic regression on soft targets (Adagrad); the last weight is the intercept."""
    w, g = np.zeros((1 << BITS) + 1), np.full((1 << BITS) + 1, 1e-6)
    rows = [np.array([*r, 1 << BITS]) for r in rows]
    for _ in range(epochs):
        for r, y in zip(rows, target):
            e = 1 / (1 + math.exp(-max(-30.0, min(30.0, w[r].sum())))) - y
            g[r] += e * e
            w[r] -= rate * e / np.sqrt(g[r])
    return w


def free(cands: list[tuple[int, int, str]], spans: list[tuple[int, int, str]]) -> list[tuple[int, int, str]]:
    """The candidates (by start, then length downwards) that overlap no span and none chosen before; one sweep over both."""
    out: list[tuple[int, int, str]] = []
    starts = sorted((s, e) for s, e, _ in spans)
    i, reach, end = 0, -1, -1  # reach: the furthest end of the spans that start before the candidate's end
    for s, e, kind in cands:
        j, far = i, reach
        while j < len(starts) and starts[j][0] < e:
            far = max(far, starts[j][1])
            j += 1
            if starts[j - 1][0] <= s:  # starts only grow: such a span counts for all later candidates
                i, reach = j, far
        if far <= s and s >= end:
            out.append((s, e, kind))
            end = e
    return out


# -- plans -------------------------------------------------------------------------------

_CAND = "array<struct<s:int,e:int,kind:string,votes:string,feats:array<int>>>"


def propose(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, base (spans), cands (candidates with votes and features)."""
    src = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    schema = T.StructType([src.schema["doc_id"], *T._parse_datatype_string(f"base array<struct<s:int,e:int,kind:string>>, cands {_CAND}").fields])

    def work():
        def act(batch: pa.RecordBatch) -> dict:
            base, cands = [], []
            for t in batch.column("text").to_pylist():
                t = t or ""
                b = base_spans(t)
                base.append([{"s": s, "e": e, "kind": k} for s, e, k in b])
                cands.append([{"s": s, "e": e, "kind": k, "votes": " ".join(map(str, votes(t, s, e, k))), "feats": features(t, s, e, k)} for s, e, k in candidates(t)])
            return {"doc_id": batch.column("doc_id"), "base": base, "cands": cands}

        return act

    return map_batches(src, work, schema)


def train(proposed: DataFrame, sample: int = SAMPLE) -> tuple[Reliability, np.ndarray]:
    """Reliabilities from all candidates' vote patterns; the classifier from about ``sample`` candidates at most, a share chosen by hash."""
    each = proposed.select("doc_id", F.explode("cands").alias("c")).select("doc_id", "c.*")
    patterns = each.groupBy("kind", "votes").count().collect()
    found = Reliability().fit([(r["kind"], r["votes"], r["count"]) for r in sorted(patterns, key=lambda r: (r["kind"], r["votes"]))])
    # the count is known, so a share by hash bounds the sample without ordering anything
    share = sample / max(1, sum(r["count"] for r in patterns))
    place = F.pmod(F.xxhash64(F.col("doc_id").cast("string"), "s", "e", "kind"), F.lit(1 << 30)) / float(1 << 30)
    rows = sorted(each.filter(place < share).select("kind", "votes", "feats").collect())
    target = np.array([found.posterior(r["kind"], r["votes"]) for r in rows])
    return found, fit_classifier([r["feats"] for r in rows], target)


def find(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone (base spans), base_sha256, spans (all, written out), n_added, n_spans."""
    proposed = written(propose(docs, id_col=id_col, text_col=text_col), "candidates")
    _, weights = train(proposed)
    schema = T.StructType([proposed.schema["doc_id"], *T._parse_datatype_string("n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long, n_spans long").fields])

    def work():
        def act(batch: pa.RecordBatch) -> dict:
            out: dict[str, list] = {f.name: [] for f in schema.fields[1:]}
            for base, cands in zip(batch.column("base").to_pylist(), batch.column("cands").to_pylist()):
                spans = [(x["s"], x["e"], x["kind"]) for x in base]
                accepted = [(c["s"], c["e"], c["kind"]) for c in cands if weights[c["feats"]].sum() + weights[-1] >= math.log(ACCEPT / (1 - ACCEPT))]
                added = free(accepted, spans)
                for k in BASE:
                    out[f"n_{k}"].append(sum(x[2] == k for x in spans))
                out["base_sha256"].append(hashlib.sha256(written_out(spans).encode()).hexdigest())
                out["spans"].append(written_out(sorted(spans + added, key=lambda x: (x[0], _ORDER[x[2]]))))
                out["n_added"].append(len(added))
                out["n_spans"].append(len(spans) + len(added))
            return {"doc_id": batch.column("doc_id"), **out}

        return act

    return map_batches(proposed, work, schema)
