"""Personal data by weak supervision: labelers vote on candidate spans, EM weighs the labelers, a classifier decides.

Strict patterns give the base spans, which always stay.  Wider patterns give further candidates.  For each
candidate a strict pattern, a gazetteer, the context, a format rule and the borders vote yes, no or not at
all.  Votes and a few coarse features are counted over all documents (a bounded number of combinations);
expectation-maximisation estimates how often each labeler is right, and a logistic span classifier is trained
on the resulting probabilities.  Candidates it accepts are added where they overlap no base span."""

from __future__ import annotations

import hashlib
import re
from bisect import bisect_left
from collections import Counter
from math import log2

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, column, slices, texts, tidy

KINDS = ("email", "ip", "card", "phone", "secret")
BASE_KINDS = 4
LABELERS = 5
ACCEPT = 0.9

_SIGNS = re.compile(r"[0-9@]")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")
# 64 and 63: the most that the standards allow for a mailbox name and a label of a domain
_SPELLED = re.compile(r"\b[A-Za-z0-9._%+-]{1,64}\s?[\[(]?(?:\bat\b|@)[\])]?\s?[A-Za-z0-9-]{1,63}(?:\s?[\[(]?(?:\bdot\b|\.)[\])]?\s?[A-Za-z0-9-]{2,63}){1,4}", re.I)
_LOOSE_PHONE = re.compile(r"(?<![\w+.-])\(?[0-9]{2,4}[)\x20./-]{1,2}[0-9]{2,4}[\x20./-][0-9]{2,5}(?:[\x20./-][0-9]{2,5})?(?![\w-])")
_SECRET = re.compile(r"(?<![A-Za-z0-9_+/=-])[A-Za-z0-9_+/=-]{20,}+(?![A-Za-z0-9_+/=-])")

# fixed values: ends of domains, issuer prefixes, calling codes, words that stand before personal data
_ENDS = frozenset("com org net edu gov io de fr es uk it nl ch at be eu info co us ca au in jp cn br ru pl se no dk fi pt mx ar".split())
_ISSUERS = ("4", "51", "52", "53", "54", "55", "34", "37", "6011", "65", "35", "2221", "23", "24", "25", "26", "270", "271", "2720")
_CODES = ("1", "7", "20", "27", "30", "31", "32", "33", "34", "36", "39", "40", "41", "43", "44", "45", "46", "47", "48", "49", "51", "52", "54", "55", "56", "57", "61", "81", "82", "86", "90", "91", "351", "353", "358")
_BEFORE = {
    "email": re.compile(r"mail|contact|correo|courriel|kontakt|write to", re.I), "ip": re.compile(r"\bip\b|host|server|addr", re.I), "card": re.compile(r"card|visa|credit|kredit|carte|tarjeta|debit", re.I),
    "phone": re.compile(r"phone|tel|call|mobil|fax|ruf", re.I), "secret": re.compile(r"token|key|secret|passw|auth|bearer|credential", re.I),
}


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if i % 2 == 0 else d * 2 - 9 * (d > 4)
    return total % 10 == 0


def _digits(text: str) -> str:
    return "".join(_DIGIT.findall(text))


def _emails(text: str) -> list[tuple[int, int]]:
    out, done, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at + 1)):
            out.append((start, m.end()))
            done = m.end()
        at = text.find("@", max(at + 1, done))
    return out


def _is_ip(match: str) -> bool:
    return all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in match.split("."))


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(kind, start, end) in the order of kinds, then starts."""
    if not _SIGNS.search(text):
        return []
    out = [(0, a, b) for a, b in _emails(text)]
    out += [(1, *m.span()) for m in _IP.finditer(text) if _is_ip(m.group())]
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 13 and 13 <= len(d := _digits(m.group())) <= 19 and luhn(d):
            out.append((2, *m.span()))
    if "+" in text:
        out += [(3, *m.span()) for m in _PHONE.finditer(text) if 9 <= len(_digits(m.group())) <= 15]
    return out


def candidates(text: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """Base spans and further candidates that overlap none of them nor one another."""
    signs = _SIGNS.search(text)
    low = None if signs else text.lower()
    if not signs and " dot " not in low and "dot)" not in low and "dot]" not in low:
        return list(base)
    taken: list[list[int]] = []  # base spans, joined where they overlap
    for a, b in sorted((a, b) for _, a, b in base):
        if taken and a < taken[-1][1]:
            taken[-1][1] = max(taken[-1][1], b)
        else:
            taken.append([a, b])
    out = list(base)

    def add(kind: int, span: tuple[int, int]) -> None:
        at = bisect_left(taken, [span[1], 0])  # the first taken span that starts at the end of this one or later
        if not at or taken[at - 1][1] <= span[0]:
            taken.insert(at, list(span))
            out.append((kind, *span))

    if "@" in text or re.search(r"\bdot\b", text, re.I):
        for m in _SPELLED.finditer(text):
            add(0, m.span())
    if signs:
        for m in _IP.finditer(text):
            add(1, m.span())
        for m in _CARD.finditer(text):
            if m.end() - m.start() >= 13 and 13 <= len(_digits(m.group())) <= 19:
                add(2, m.span())
        for m in _LOOSE_PHONE.finditer(text):
            if 9 <= len(_digits(m.group())) <= 15:
                add(3, m.span())
        for m in _SECRET.finditer(text):
            s = m.group()
            if any(c.isdigit() for c in s) and any(c.isalpha() for c in s):
                add(4, m.span())
    return out


def _entropy(s: str) -> float:
    return -sum(n / len(s) * log2(n / len(s)) for n in Counter(s).values())


def votes(text: str, kind: int, a: int, b: int, strict: bool) -> tuple[tuple[int, ...], tuple[int, ...]]:
    """Votes (1 yes, 0 no, 2 none) and coarse features of a candidate."""
    span, digits = text[a:b], _digits(text[a:b])
    name = KINDS[kind]
    if name == "email":
        listed = int(re.split(r"[\s.\[\]()]+", span.rstrip(")]."))[-1].lower() in _ENDS)
        form = int("@" in span and "." in span.rpartition("@")[2])
    elif name == "ip":
        first = span.split(".")[0].lstrip("0") or "0"
        listed = 0 if first in ("0", "255") else 2
        form = int(_is_ip(span))
    elif name == "card":
        listed, form = int(digits.startswith(_ISSUERS)), int(luhn(digits))
    elif name == "phone":
        listed = int(digits.startswith(_CODES)) if span.startswith("+") else 2
        form = int(span.startswith(("+", "(")) and len(digits) >= 10) if len(digits) != 9 else 2
    else:
        listed = int(bool(re.fullmatch(r"[0-9a-fA-F]+|[A-Z0-9]+", span))) or 2
        form = int(_entropy(span) >= 3.0)
    ctx = text[max(0, a - 32) : a]
    context = 1 if _BEFORE[name].search(ctx) else 2
    left, right = text[a - 1 : a], text[b : b + 1]
    border = int(not (left.isalnum() or right.isalnum()))
    strict_vote = 2 if name == "secret" else int(strict)
    shape = (min(3, (b - a) // 12), 0 if not digits else 1 if len(digits) < len(span) / 2 else 2, 0 if not left or left.isspace() else 1 if left in "\"'=:([<" else 2)
    return (strict_vote, listed, context, form, border), shape


def expectation_maximisation(patterns: np.ndarray, weight: np.ndarray, rounds: int = 50) -> tuple[float, np.ndarray, np.ndarray]:
    """Share of true spans, P(vote 1 | class, labeler) and P(true) of each vote pattern (1, 0, 2: none)."""
    said = patterns != 2
    yes = (patterns == 1) & said
    score = (yes.sum(1) + 0.5) / (said.sum(1) + 1.0)
    truth, prior, right = np.clip(score, 0.05, 0.95), 0.5, np.full((2, LABELERS), 0.5)
    for _ in range(rounds):
        for c, p in ((0, 1 - truth), (1, truth)):
            mass = (weight * p)[:, None]
            lean = 4.0 if c else 1.0  # a weak belief that labelers beat chance: four yes of five, or one
            right[c] = ((mass * yes).sum(0) + lean) / ((mass * said).sum(0) + 5.0)
        prior = ((weight * truth).sum() + 1) / (weight.sum() + 2)
        odds = np.log(prior / (1 - prior)) + (np.where(yes, np.log(right[1] / right[0]), np.log((1 - right[1]) / (1 - right[0]))) * said).sum(1)
        truth = 1 / (1 + np.exp(-np.clip(odds, -30, 30)))
    return prior, right, truth


def _code(vote: tuple[int, ...], shape: tuple[int, ...]) -> int:
    out = 0
    for x, size in zip((*vote, *shape), (3,) * LABELERS + (4, 3, 3), strict=True):
        out = out * size + x
    return out


def _onehot(codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Vote patterns and 0/1 features of codes."""
    rest, cols = codes.copy(), []
    for size in (3, 3, 4, *(3,) * LABELERS):
        cols.append((rest % size, size))
        rest //= size
    cols = cols[::-1]
    hot = [np.ones((len(codes), 1))] + [(v[:, None] == np.arange(s)).astype(float) for v, s in cols]
    return np.stack([v for v, _ in cols[:LABELERS]], 1), np.hstack(hot)


def train_classifier(counts: dict[tuple[int, int], int]) -> dict[int, np.ndarray]:
    """Logistic weights by kind, from counts of (kind, code)."""
    out = {}
    for kind in range(len(KINDS)):
        own = sorted((c, n) for (k, c), n in counts.items() if k == kind)
        if not own:
            continue
        codes, n = np.array([c for c, _ in own], np.int64), np.array([x for _, x in own], float)
        patterns, x = _onehot(codes)
        truth = expectation_maximisation(patterns, n)[2]
        w, n = np.zeros(x.shape[1]), n / n.sum() * min(n.sum(), 1e4)
        for _ in range(30):  # Newton steps with a ridge
            p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
            slope = x.T @ (n * (truth - p)) - 0.1 * w
            bend = (x * (n * p * (1 - p))[:, None]).T @ x + 0.1 * np.eye(len(w))
            w += np.linalg.solve(bend, slope)
        out[kind] = w
    return out


def count_votes(docs: DataFrame) -> dict[tuple[int, int], int]:
    """Over all documents; at most kinds * 3**5 * 36 combinations reach the driver."""

    def make():
        def step(batch):
            seen: Counter[tuple[int, int]] = Counter()
            for raw in texts(batch):
                text = raw.decode()
                base = base_spans(text)
                strict = set(base)
                for c in candidates(text, base):
                    seen[c[0], _code(*votes(text, *c, strict=c in strict))] += 1
            return {"kind": pa.array([k for k, _ in seen], pa.int32()), "code": pa.array([c for _, c in seen], pa.int64()), "n": pa.array(list(seen.values()), pa.int64())}

        return step

    rows = arrow_map(docs.select("text"), make, "kind int, code long, n long").groupBy("kind", "code").agg(F.sum("n").alias("n"))
    return {(r["kind"], r["code"]): r["n"] for r in rows.collect()}


class Finder:
    """All spans of a text: base spans, and candidates that the classifier accepts."""

    def __init__(self, weights: dict[int, np.ndarray]):
        self.weights, self.known = weights, {}

    def accepts(self, kind: int, code: int) -> bool:
        if (found := self.known.get((kind, code))) is None:
            w = self.weights.get(kind)
            p = 0.0 if w is None else 1 / (1 + np.exp(-np.clip((_onehot(np.array([code]))[1] @ w)[0], -30, 30)))
            found = self.known[kind, code] = bool(p >= ACCEPT)
        return found

    def __call__(self, text: str) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]:
        base = base_spans(text)
        strict = set(base)
        more = [c for c in candidates(text, base) if c not in strict and self.accepts(c[0], _code(*votes(text, *c, strict=False)))]
        return base, sorted(base + more)


def _joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for k, a, b in spans)


def report(docs: DataFrame) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_spans (base and added) for every row.

    Null texts count as empty and have no spans; equal texts get equal results, repeated rows and null ids stay;
    other columns are ignored; an empty table gives an empty one."""
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    shared = docs.sparkSession.sparkContext.broadcast(train_classifier(count_votes(base)))

    def make():
        find = Finder(shared.value)

        def step(batch):
            counts, sha, spans, total = [[] for _ in range(BASE_KINDS)], [], [], []
            for raw in texts(batch):
                strict, every = find(raw.decode())
                for k, c in enumerate(counts):
                    c.append(sum(s[0] == k for s in strict))
                sha.append(hashlib.sha256(_joined(strict).encode()).hexdigest())
                spans.append(_joined(every))
                total.append(len(every))
            named = {f"n_{KINDS[k]}": pa.array(c, pa.int64()) for k, c in enumerate(counts)}
            return {"doc_id": column(batch, "doc_id")} | named | {"base_sha256": pa.array(sha, pa.string()), "spans": pa.array(spans, pa.string()), "n_spans": pa.array(total, pa.int64())}

        return step

    return arrow_map(base, make, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_spans long", slice_by="text")


def masked(text: str, spans: list[tuple[int, int, int]]) -> str:
    """Spans replaced by their kind in capitals; spans that overlap become one."""
    out, end = [], 0
    for k, a, b in sorted(spans, key=lambda s: (s[1], -s[2])):
        if a >= end:
            out += [text[end:a], f"[{KINDS[k].upper()}]"]
        end = max(end, b)
    return "".join([*out, text[end:]])


def redact(docs: DataFrame) -> DataFrame:
    """Rows of docs, all columns; text with personal data masked, and n_chars (if there) of the new text.

    Null texts stay null, texts without spans stay as they are, repeated rows stay; an empty table gives an empty one."""
    shared = docs.sparkSession.sparkContext.broadcast(train_classifier(count_votes(docs)))
    at = docs.columns.index("text")
    chars = docs.columns.index("n_chars") if "n_chars" in docs.columns else None

    def run(batches):
        find = Finder(shared.value)
        for batch in (part for whole in batches for part in slices(whole, at)):
            old = batch.column(at).to_pylist()
            new = [x if x is None else masked(x, s) if (s := find(x)[1]) else x for x in old]
            cols = list(batch.columns)
            cols[at] = pa.array(new, batch.schema.types[at])
            if chars is not None:
                n = [k if o == t else len(t) for k, o, t in zip(cols[chars].to_pylist(), old, new, strict=True)]
                cols[chars] = pa.array(n, batch.schema.types[chars])
            yield pa.RecordBatch.from_arrays(cols, names=batch.schema.names)

    return docs.mapInArrow(tidy(run), docs.schema)
