"""Benchmark decontamination: word windows of test items, looked up in every window of every document."""

from __future__ import annotations

import hashlib
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, column, slices, table, tidy

#: Lower-cases A-Z; whatever is no digit, letter or non-ASCII byte becomes a space.
_NORMAL = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
_B = np.uint64(0x9E3779B97F4A7C15)


def words_of(text: bytes) -> list[bytes]:
    return text.translate(_NORMAL).split()


def window_hash(ids: np.ndarray, size: int) -> np.ndarray:
    n = len(ids) - size + 1
    out = np.zeros(max(n, 0), np.uint64)
    for k in range(size):
        out *= _B
        out += ids[k : k + n]
    return out ^ (out >> np.uint64(29))


class WindowIndex:
    """Exact windows of test items, by length: sorted hashes to find candidates, word ids to verify them.

    ``items``: (id or None, text).  Rows with one id are one item; hits of items without an id count, but have
    no name.  Beside the vocabulary this takes some 30 bytes for each word of the items, in flat arrays."""

    def __init__(self, items: list[tuple[str | None, bytes]], size: int):
        self.vocabulary: dict[bytes, int] = {}
        self.names: list[str] = []
        numbers: dict[str, int] = {}
        flat, starts, owners, lengths, at = [], [], [], [], 0
        for name, text in items:
            words = words_of(text)
            if not words:
                continue
            flat.append(np.array([self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words], np.uint32))
            length = min(size, len(words))
            count = len(words) - length + 1
            owner = -1 if name is None else numbers.setdefault(name, len(numbers))
            starts.append(np.arange(at, at + count))
            owners.append(np.full(count, owner))
            lengths.append(np.full(count, length))
            at += len(words)
        self.names = list(numbers)
        self.flat = np.concatenate([np.zeros(0, np.uint32), *flat])
        start, owner, length = (np.concatenate([np.zeros(0, np.int64), *x]) for x in (starts, owners, lengths))
        self.by_length = {int(k): self._group(start[length == k], owner[length == k], int(k)) for k in np.unique(length)}

    def _group(self, start: np.ndarray, owner: np.ndarray, size: int) -> tuple[np.ndarray, ...]:
        """Hashes of the distinct windows in order, where each stands first, and the items of each."""
        rows = np.ascontiguousarray(self.flat[start[:, None] + np.arange(size)])
        _, first, group = np.unique(rows.view(np.dtype((np.void, 4 * size))).ravel(), return_index=True, return_inverse=True)
        hashes = window_hash(rows[first].ravel().astype(np.uint64), size)[::size]
        order = np.argsort(hashes, kind="stable")
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        pairs = np.unique(np.stack([place[group], owner], 1), axis=0)
        ends = np.searchsorted(pairs[:, 0], np.arange(len(order) + 1))
        return hashes[order], start[first[order]].astype(np.uint32), ends.astype(np.uint32), pairs[:, 1].astype(np.int32)

    def scan(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set[int]]:
        """Hit windows as (start, end), in no order, and items with a window here."""
        ids = np.fromiter(map(self.vocabulary.get, words, repeat(0)), np.uint32, len(words))
        gaps = np.concatenate([[0], np.cumsum(ids == 0)])
        spans, found = [], set()
        for size, (known, first, ends, owners) in self.by_length.items():
            if len(ids) < size:
                continue
            at = np.flatnonzero(gaps[size:] == gaps[:-size])
            if not len(at):
                continue
            hashes = window_hash(ids.astype(np.uint64), size)[at]
            low = np.searchsorted(known, hashes)
            near = np.minimum(low, len(known) - 1)
            groups = set()
            for k in np.flatnonzero(known[near] == hashes).tolist():
                i, g = int(at[k]), int(low[k])
                while g < len(known) and known[g] == hashes[k]:
                    if np.array_equal(self.flat[first[g] : first[g] + size], ids[i : i + size]):
                        spans.append((i, i + size))
                        groups.add(g)
                    g += 1
            for g in groups:
                found.update(owners[ends[g] : ends[g + 1]].tolist())
        found.discard(-1)
        return spans, found


#: Bytes of item text to an index.  Measured: 4.6 MB of text with all windows different, of 220,000 different
#: words, are 13 MB as broadcast and 38 MB in a Python worker.
LIMIT = 4 << 20
_SPANS = "array<struct<a: long, b: long>>"


def _blocks(benchmark: DataFrame, limit: int) -> list:
    """Loaders of the items of the benchmark, in blocks of about ``limit`` bytes of text at most."""
    items = benchmark.select(F.col("item_id").cast("string").alias("item_id"), "text").filter("text is not null")
    size = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = -(-size // limit) or 1
    block = lambda k: items.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == k) if parts > 1 else items
    return [(lambda k=k: [(r[0], r[1].encode()) for r in block(k).collect()]) for k in range(parts)]


def _hits(rows: DataFrame, index: WindowIndex, names: tuple[str, str, str], hit_only: bool) -> DataFrame:
    """All columns of rows (one of them ``text``) with the number of words, merged hit spans and items."""
    shared = rows.sparkSession.sparkContext.broadcast(index)
    at = rows.columns.index("text")
    n, spans, items = names
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema), f"`{n}` long, `{spans}` {_SPANS}, `{items}` array<string>"])
    kind = pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())]))

    def run(batches):
        own = shared.value
        for batch in (part for whole in batches for part in slices(whole, at)):
            count, found_spans, found_items = [], [], []
            for text in batch.column(at).cast(pa.binary()).to_pylist():
                words = words_of(text or b"")
                hits, found = own.scan(words)
                count.append(len(words))
                found_spans.append([{"a": a, "b": b} for a, b in _merged(hits)])
                found_items.append([own.names[i] for i in found])
            more = [pa.array(count, pa.int64()), pa.array(found_spans, kind), pa.array(found_items, pa.list_(pa.string()))]
            out = pa.RecordBatch.from_arrays([*batch.columns, *more], names=[*batch.schema.names, *names])
            yield out.filter(pa.array([bool(x) for x in found_spans], pa.bool_())) if hit_only else out

    return rows.mapInArrow(tidy(run), schema)


def _judged(rows: DataFrame, benchmark: DataFrame, size: int, limit: int) -> tuple[DataFrame, tuple[str, str, str]]:
    """Rows with every column they had, and the names of three more: number of words, merged spans, items.

    One index is broadcast up to ``limit`` bytes of item text.  A larger benchmark is worked off in blocks, each
    against the whole input; only rows with hits go on from there and are brought together by a written row key."""
    own = lambda tag: next(c for k in range(len(rows.columns) + 1) if (c := f"{tag}_{k}") not in rows.columns)
    names = own("n_words"), own("spans"), own("items")
    blocks = _blocks(benchmark, limit)
    if len(blocks) == 1:
        return _hits(rows, WindowIndex(blocks[0](), size), names, False), names
    key = own("row")
    rows = table(rows.withColumn(key, F.monotonically_increasing_id()), "decontam")
    every = None
    for block in blocks:
        part = _hits(rows.select(key, "text"), WindowIndex(block(), size), names, True).drop("text")
        every = part if every is None else every.unionByName(part)
    n, spans, items = names
    every = every.groupBy(key).agg(F.flatten(F.collect_list(spans)).alias(spans), F.array_distinct(F.flatten(F.collect_list(items))).alias(items))

    def merge(batches):
        kind = pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())]))
        for batch in batches:
            merged = [[{"a": a, "b": b} for a, b in _merged([(x["a"], x["b"]) for x in row])] for row in column(batch, spans).to_pylist()]
            yield pa.RecordBatch.from_arrays([column(batch, key), pa.array(merged, kind), column(batch, items)], names=[key, spans, items])

    every = every.mapInArrow(tidy(merge), f"`{key}` long, `{spans}` {_SPANS}, `{items}` array<string>")
    words = F.regexp_count(F.coalesce("text", F.lit("")), F.lit(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"))
    out = rows.join(every, key, "left").withColumn(n, words.cast("long"))
    return out.withColumns({spans: F.coalesce(spans, F.lit([]).cast(_SPANS)), items: F.coalesce(items, F.lit([]).cast("array<string>"))}), names


def scan(docs: DataFrame, benchmark: DataFrame, size: int = 10, limit: int = LIMIT) -> DataFrame:
    """Per row of docs: doc_id, n_words, spans (merged hit ranges of words, end exclusive), items (distinct ids).

    Null or wordless texts have no words and no hits; items without words are left out, rows of one item_id are
    one item, an item without an id hits but has no name; repeated rows are judged alike; other columns are
    ignored; an empty benchmark hits nothing.  limit: see LIMIT; it changes no result."""
    judged, names = _judged(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), benchmark, size, limit)
    return judged.select("doc_id", *[F.col(x).alias(y) for x, y in zip(names, ("n_words", "spans", "items"), strict=True)])


def _merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            if b > out[-1][1]:
                out[-1] = (out[-1][0], b)
        else:
            out.append((a, b))
    return out


def report(docs: DataFrame, benchmark: DataFrame, size: int = 10, limit: int = LIMIT) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated for every row of docs; see scan."""
    hits = scan(docs, benchmark, size, limit)
    n_hit = F.aggregate("spans", F.lit(0).cast("long"), lambda n, s: n + s["b"] - s["a"])
    items = F.array_sort("items")
    return hits.select("doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join(items, ","), 256).alias("items_sha256"), (n_hit > 0).alias("contaminated"))


def remove_documents(docs: DataFrame, benchmark: DataFrame, size: int = 10, limit: int = LIMIT) -> DataFrame:
    """Rows of docs, all columns, without those that hold a window of a test item.

    Null, empty and wordless texts stay, as do repeated rows without a hit; see scan."""
    judged, (_, spans, _) = _judged(docs, benchmark, size, limit)
    return judged.filter(F.size(spans) == 0).select(*[f"`{c}`" for c in docs.columns])


def remove_spans(docs: DataFrame, benchmark: DataFrame, size: int = 10, limit: int = LIMIT) -> DataFrame:
    """doc_id and text with the hit words cut out, as judged on the text given; what parts words outside of the
    spans stays as it is.  Null texts stay null, repeated rows stay, other columns are ignored; see scan."""
    import re

    judged, (_, spans, _) = _judged(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), benchmark, size, limit)
    word = re.compile(rb"[0-9a-z\x80-\xff]+")

    def clean(text: bytes, cut: list[dict]) -> bytes:
        found = [m.span() for m in word.finditer(text.translate(_NORMAL))]
        kept, at = [], 0
        for x in cut:
            kept.append(text[at : found[x["a"]][0]])
            at = found[x["b"] - 1][1]
        return b"".join([*kept, text[at:]])

    def make():
        def step(batch):
            raw = column(batch, "text").cast(pa.binary()).to_pylist()
            out = [t if t is None or not cut else clean(t, cut) for t, cut in zip(raw, column(batch, "spans").to_pylist(), strict=True)]
            return {"doc_id": column(batch, "doc_id"), "text": pa.array(out, pa.binary()).cast(pa.string())}

        return step

    return arrow_map(judged.select("doc_id", "text", F.col(spans).alias("spans")), make, "doc_id long, text string", slice_by="text")
