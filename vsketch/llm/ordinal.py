"""Ordinal cumulative-link regression on hashed text: one weight vector, ordered thresholds.

P(grade > k | x) = sigmoid(w.x - t_k) with t_0 < t_1 < ..  Features are hashed words, word shapes and a few
binned statistics of the text, each present or not.  Fitted on a bounded sample of graded rows, in which only
features whose presence depends on the grade (likelihood-ratio test) get a weight; scoring covers all rows."""

from __future__ import annotations

import re
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, column, table, texts

BITS = 20
_SHAPE = bytes(97 if 97 <= c <= 122 else 65 if 65 <= c <= 90 else 48 if 48 <= c <= 57 else 122 if c >= 128 else c for c in range(256))
_RUN = re.compile(rb"(.)\1+", re.DOTALL)
_EDGE = b".,;:!?\"'()[]{}<>*#%&$@^~`|\\/_-+="


def _bin(x: float, edges: tuple[float, ...]) -> int:
    return sum(x >= e for e in edges)


def features(text: bytes, with_words: bool = True) -> np.ndarray:
    """Sorted distinct feature numbers under 2**BITS."""
    words = text.split()
    names = set()
    if with_words:
        low = {w.strip(_EDGE) for w in text.lower().split()}
        names.update(b"w" + w for w in low if w)
    shapes: dict[bytes, int] = {}
    for w in words:
        s = w.translate(_SHAPE)
        shapes[s] = shapes.get(s, 0) + 1
    folded: dict[bytes, int] = {}
    for s, n in shapes.items():
        s = _RUN.sub(rb"\1", s)
        folded[s] = folded.get(s, 0) + n
    total = max(1, len(words))
    names.update(b"s" + s + b"%d" % _bin(n / total, (0.02, 0.1, 0.3)) for s, n in folded.items() if n / total >= 0.005 or n == total)
    size = max(1, len(text))
    plain = text.translate(_SHAPE)
    upper, lower, other, digit = plain.count(b"A"), plain.count(b"a"), plain.count(b"z"), plain.count(b"0")
    sign = size - upper - lower - other - digit - sum(text.count(c) for c in (b" ", b"\n", b"\t", b"\r"))
    fresh = len(set(words)) / total ** 0.75
    stats = (
        ("upper", upper / max(1, upper + lower), (0.02, 0.1, 0.25, 0.5, 0.8)), ("sign", sign / size, (0.01, 0.03, 0.06, 0.12, 0.25)), ("digit", digit / size, (0.01, 0.05, 0.15, 0.4)),
        ("fresh", fresh, (0.1, 0.3, 0.6, 1.0, 1.5)), ("long", len(text) / total, (3, 4.5, 6, 8, 12)), ("words", len(words), (1, 3, 8, 20, 60, 200, 1000)), ("lines", text.count(b"\n") / total, (0.01, 0.05, 0.2, 0.5)),
        ("most", max(shapes.values(), default=0) / total, (0.2, 0.5, 0.8, 0.95)),
    )
    names.update(b"=%s%d" % (n.encode(), _bin(x, e)) for n, x, e in stats)
    mask = (1 << BITS) - 1
    return np.unique(np.fromiter((xxhash.xxh3_64_intdigest(n) & mask for n in names), np.int64, len(names)))


@dataclass
class Ordinal:
    """Weights by feature number, thresholds, and the grades they part."""

    grades: list[int]
    thresholds: np.ndarray
    weights: np.ndarray = field(default_factory=lambda: np.zeros(1 << BITS, np.float32))
    with_words: bool = True

    def latent(self, text: bytes) -> float:
        return float(self.weights[features(text, self.with_words)].sum())

    def tails(self, latent: np.ndarray) -> np.ndarray:
        """P(grade > k) for each row and threshold."""
        return 1 / (1 + np.exp(np.clip(self.thresholds[None, :] - latent[:, None], -60, 60)))

    def expected(self, latent: np.ndarray) -> np.ndarray:
        steps = np.diff(np.array(self.grades, float))
        return self.grades[0] + self.tails(latent) @ steps if len(steps) else np.full(len(latent), float(self.grades[0]))


def screen(rows: list[np.ndarray], grade: np.ndarray, least: float) -> np.ndarray:
    """Features whose likelihood-ratio statistic of presence against grade is at least ``least``."""
    n, kinds = len(rows), int(grade.max()) + 1 if len(grade) else 1
    flat = np.concatenate(rows)
    which, at = np.unique(flat, return_inverse=True)
    there = np.zeros((kinds, len(which)))
    np.add.at(there, (np.repeat(grade, [len(r) for r in rows]), at), 1)
    size = np.bincount(grade, minlength=kinds).astype(float)[:, None]
    part = lambda o, e: np.where(o > 0, o * np.log(np.maximum(o, 1e-9) / np.maximum(e, 1e-9)), 0)
    p = there.sum(0) / n
    g = 2 * (part(there, size * p) + part(size - there, size * (1 - p))).sum(0)
    return which[g >= least]


def screened(rows: DataFrame, sizes: dict[int, int], least: float) -> np.ndarray:
    """The same over a table (grade, found) in Spark; only features that pass reach the driver (2**BITS at most)."""
    total = sum(sizes.values())
    there = {g: F.sum(F.when(F.col("grade") == g, 1.0).otherwise(0.0)) for g in sizes}
    counts = rows.select("grade", F.explode("found").alias("f")).groupBy("f").agg(*[c.alias(f"n{g}") for g, c in there.items()])
    part = lambda o, e: F.when(o > 0, o * F.log(o / e)).otherwise(0.0)
    p = sum((F.col(f"n{g}") for g in sizes), F.lit(0.0)) / total
    g2 = F.lit(0.0)
    for g, n in sizes.items():
        g2 += part(F.col(f"n{g}"), p * n) + part(n - F.col(f"n{g}"), n * (1 - p))
    return np.sort(np.asarray(counts.filter(2 * g2 >= least * (1 - 1e-9)).select("f").toArrow().column(0)).astype(np.int64))


def fit(rows: list[np.ndarray], grades_of: list[int], least: float = 12.0, ridge: float = 0.5, steps: int = 400, with_words: bool = True) -> Ordinal:
    """Maximum likelihood with a ridge, by Adam on all rows; grades weigh alike."""
    grades = sorted(set(grades_of))
    if len(grades) < 2:
        return Ordinal(grades or [0], np.zeros(0), with_words=with_words)
    grade = np.searchsorted(grades, grades_of)
    chosen = screen(rows, grade, least)
    own = [np.searchsorted(chosen, r[np.isin(r, chosen)]) for r in rows]
    flat, row = np.concatenate(own).astype(np.int64), np.repeat(np.arange(len(rows)), [len(r) for r in own])
    k = len(grades) - 1
    above = (grade[:, None] > np.arange(k)[None, :]).astype(float)
    weight = (len(grade) / (len(grades) * np.bincount(grade)))[grade]
    w, t0, gaps = np.zeros(len(chosen)), 0.0, np.zeros(max(0, k - 1))
    state = [np.zeros_like(w), np.zeros_like(w), np.zeros(k), np.zeros(k)]
    for i in range(1, steps + 1):
        t = t0 + np.concatenate([[0.0], np.cumsum(np.exp(gaps))])
        latent = np.bincount(row, w[flat], len(rows))
        p = 1 / (1 + np.exp(np.clip(t[None, :] - latent[:, None], -60, 60)))
        low, high = np.hstack([np.ones((len(p), 1)), p]), np.hstack([p, np.zeros((len(p), 1))])
        at = np.arange(len(p)), grade
        chance = np.maximum(low[at] - high[at], 1e-12)
        slope_low = np.where(grade > 0, low[at] * (1 - low[at]), 0)
        slope_high = np.where(grade < k, high[at] * (1 - high[at]), 0)
        d = weight * (slope_low - slope_high) / chance  # by the latent score
        grad_w = np.bincount(flat, d[row], len(chosen)) - ridge * w
        by_t = np.zeros(k)
        np.add.at(by_t, np.maximum(grade - 1, 0), -weight * slope_low / chance)
        np.add.at(by_t, np.minimum(grade, k - 1), weight * slope_high / chance)
        grad_t = np.concatenate([[by_t.sum()], [by_t[j + 1 :].sum() * np.exp(gaps[j]) for j in range(k - 1)]])
        rate = 0.1 * (1 - i / (steps + 1))
        for x, g, m, v in ((w, grad_w, state[0], state[1]), (None, grad_t, state[2], state[3])):
            m += 0.1 * (g - m)
            v += 0.01 * (g * g - v)
            move = rate * (m / (1 - 0.9**i)) / (np.sqrt(v / (1 - 0.99**i)) + 1e-8)
            if x is None:
                t0 += move[0]
                gaps += move[1:]
            else:
                x += move
    out = Ordinal(grades, t0 + np.concatenate([[0.0], np.cumsum(np.exp(gaps))]), with_words=with_words)
    out.weights[chosen] = w
    return out


CELLS = 4096


def sample(docs: DataFrame, labels: DataFrame, grade: str, bound: int) -> DataFrame:
    """doc_id, text, grade of at most ``bound`` labelled rows of each grade, the lowest by a hash of doc_id.

    A count by grade and hash cell tells up to which cell a grade's rows are needed; only those are put in
    order, so a grade that holds nearly all rows doesn't land in one task.  Null ids, grades and texts are left out,
    repeated labels count once; there should be few grades (each is a row of the count)."""
    from pyspark.sql import Window

    marks = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(grade).cast("int").alias("grade")).filter("doc_id is not null and grade is not null").distinct()
    marks = marks.withColumn("cell", F.pmod(F.xxhash64("doc_id"), F.lit(CELLS)).cast("int"))
    upto: dict[int, int] = {}
    seen: dict[int, int] = {}
    for r in sorted(marks.groupBy("grade", "cell").count().collect()):
        if seen.get(r["grade"], 0) < bound:
            seen[r["grade"]], upto[r["grade"]] = seen.get(r["grade"], 0) + r["count"], r["cell"]
    if not upto:
        marks = marks.limit(0)
    else:
        marks = marks.filter(F.create_map(*[F.lit(x) for g, c in upto.items() for x in (g, c)])[F.col("grade")] >= F.col("cell"))
    nth = F.row_number().over(Window.partitionBy("grade").orderBy("cell", F.xxhash64("doc_id"), "doc_id"))
    marks = marks.withColumn("nth", nth).filter(F.col("nth") <= bound).select("doc_id", "grade")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(marks), "doc_id").filter("text is not null")


def train(docs: DataFrame, labels: DataFrame, grade: str, bound: int = 1500, least: float = 12.0, with_words: bool = True, **how) -> Ordinal:
    """``bound``: the most labelled rows of each grade that are used (all where there are fewer); ``least``: see screen.

    Rows go to the driver with the features that pass the screening only."""

    def make():
        def step(batch):
            found = [features(t, with_words).astype(np.int32) for t in texts(batch)]
            return {"doc_id": column(batch, "doc_id"), "grade": column(batch, "grade"), "found": pa.array(found, pa.list_(pa.int32()))}

        return step

    rows = table(arrow_map(sample(docs, labels, grade, bound), make, "doc_id long, grade int, found array<int>", slice_by="text"), "graded")
    sizes = {r["grade"]: r["count"] for r in sorted(rows.groupBy("grade").count().collect())}
    if len(sizes) < 2:
        return fit([], list(sizes), with_words=with_words)
    chosen = screened(rows, sizes, least)

    def kept(batches):
        for batch in batches:
            found = [x[np.isin(x, chosen)] for x in (np.array(x, np.int32) for x in column(batch, "found").to_pylist())]
            yield pa.RecordBatch.from_arrays([column(batch, "doc_id"), column(batch, "grade"), pa.array(found, pa.list_(pa.int32()))], names=["doc_id", "grade", "found"])

    rows = rows.mapInArrow(kept, rows.schema).toArrow().to_pylist()
    rows.sort(key=lambda r: (r["doc_id"], r["grade"], r["found"]))  # the same model whatever the order of tasks
    return fit([np.array(r["found"], np.int64) for r in rows], [r["grade"] for r in rows], least=least, with_words=with_words, **how)


def grade(docs: DataFrame, model: Ordinal, at: int | None = None) -> DataFrame:
    """doc_id, expected, tail (P of a grade over ``at``, by default the lowest) for every row; null texts count as empty.
    Repeated rows and null ids stay; other columns are ignored; an empty table gives an empty one."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    k = 0 if at is None else int(np.searchsorted(model.grades, at))

    def make():
        own = shared.value

        def step(batch):
            latent = np.array([own.latent(t) for t in texts(batch)])
            tails = own.tails(latent)
            tail = tails[:, k] if tails.shape[1] > k else np.zeros(len(latent))
            return {"doc_id": column(batch, "doc_id"), "expected": pa.array(own.expected(latent)), "tail": pa.array(tail)}

        return step

    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return arrow_map(base, make, "doc_id long, expected double, tail double", slice_by="text")
