"""Substring dedup: rolling hashes of every fixed-length word window, repeated windows merged into removal spans.

Three rounds, each exact.  (1) Every window has a minimizer, the smallest hash of the shorter grams inside it;
equal windows have equal minimizers, so only windows whose minimizer occurs twice can repeat.  Minimizers are
counted by hash ranges, packed in sorted blocks.  (2) The windows that are left are compared by a 64-bit
rolling hash within evenly dealt parts; all but the first by (doc_id, start) are removed.
(3) Removed windows merge into maximal spans of words.  Each block of rows reduces what it sees twice to one
entry before anything is dealt out, so a passage that a third of the documents share stays small."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, column, slices, table, texts, tidy, unique_ids

_B = np.uint64(0x9E3779B97F4A7C15)
_M = np.uint64(0xFF51AFD7ED558CCD)
BLOCK_WORDS = 1_500_000
BLOCK_BYTES = 16 << 20


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))


def rolling(h: np.ndarray, size: int) -> np.ndarray:
    """A mixed polynomial hash of each run of ``size`` word hashes (needs len(h) >= size)."""
    n = len(h) - size + 1
    out = np.zeros(n, np.uint64)
    for k in range(size):
        out *= _B
        out += h[k : k + n]
    out ^= out >> np.uint64(32)
    out *= _M
    out ^= out >> np.uint64(29)
    return out


def sliding_min(h: np.ndarray, size: int) -> np.ndarray:
    """The least of each ``size`` neighbours, by doubling."""
    out, width = h, 1
    while 2 * width <= size:
        out = np.minimum(out[:-width], out[width:])
        width *= 2
    return np.minimum(out[: len(out) - (size - width)], out[size - width :]) if width < size else out


def minimizers(h: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, np.ndarray]:
    """Gram hashes, and the minimizer of each window."""
    grams = rolling(h, gram)
    return grams, sliding_min(grams, window - gram + 1)


def _ranges(docs: DataFrame, gram: int) -> int:
    """Bits of the hash that choose a range: about half a million minimizers in each."""
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    return max(0, int(np.ceil(np.log2(max(1, size / 36 / 500_000)))))


def _deal(key: np.ndarray, bits: int) -> np.ndarray:
    """A part for each window by its minimizer, so that neighbours stay together and make few spans.  Ranges of minimizers
    won't do: they are the least of many hashes, so the lowest range would hold most windows."""
    mixed = key * _B
    return ((mixed ^ mixed >> np.uint64(32)) * _M >> np.uint64(63 - bits)).astype(np.int64)


def _split(parts: np.ndarray) -> list[tuple[int, slice]]:
    """Runs of equal values in a sorted array; none in an empty one."""
    if not len(parts):
        return []
    at = np.flatnonzero(np.r_[True, parts[1:] != parts[:-1]])
    return [(int(parts[a]), slice(a, b)) for a, b in zip(at, [*at[1:], len(parts)], strict=True)]


def _offsets(x: np.ndarray) -> tuple[int, bytes]:
    """Ids as a base and 4-byte distances, or as 8-byte numbers with base -1 where they are far apart."""
    if len(x) and int(x.max()) - int(x.min()) < 1 << 32 and int(x.min()) >= 0:
        return int(x.min()), (x - x.min()).astype(np.uint32).tobytes()
    return -1, x.astype(np.int64).tobytes()


def _ids(base: int, data: bytes) -> np.ndarray:
    return np.frombuffer(data, np.int64) if base == -1 else np.frombuffer(data, np.uint32).astype(np.int64) + base


_SCAN = pa.schema([("part", pa.int32()), ("doc_id", pa.int64()), ("n_words", pa.int64()), ("digest", pa.binary()), ("keys", pa.binary()), ("low", pa.binary()), ("base", pa.int64()), ("docs", pa.binary()), ("twice", pa.binary())])
_SCAN_SQL = "part int, doc_id long, n_words long, digest binary, keys binary, low binary, base long, docs binary, twice binary"


def _scan(docs: DataFrame, window: int, gram: int, bits: int) -> DataFrame:
    """Rows with part -1: doc_id, n_words, digest of the words, keys known to repeat.  Others: packed keys of a range."""
    shift = np.uint64(64 - 32 - bits)

    def block(ids: list[int], n_words: list[int], digests: list[bytes], found: list[tuple[int, np.ndarray, np.ndarray]]) -> list[dict]:
        rows = [{"part": -1, "doc_id": d, "n_words": n, "digest": g} for d, n, g in zip(ids, n_words, digests, strict=True)]
        if not found:
            return rows
        key = np.concatenate([k for _, k, _ in found])
        own = np.repeat(np.arange(len(found)), [len(k) for _, k, _ in found])
        twice = np.concatenate([t for _, _, t in found])
        order = np.argsort(key, kind="stable")
        key, own, twice = key[order], own[order], twice[order]
        first = np.r_[True, key[1:] != key[:-1]]
        at = np.flatnonzero(first)
        n = np.diff(np.r_[at, len(key)])
        group = np.cumsum(first) - 1
        several = (n > 1) | np.logical_or.reduceat(twice, at)
        local = several[group]
        here = np.lexsort((key[local], own[local]))
        who, what = own[local][here], key[local][here]
        for f, span in _split(who):
            rows[found[f][0]]["keys"] = what[span].tobytes()
        key, doc, several = key[at], np.array([ids[found[f][0]] for f in own[at]], np.int64), several
        for part, span in _split((key >> np.uint64(32)).astype(np.int64)):
            base, packed = _offsets(doc[span])
            rows.append({"part": part, "low": (key[span] & np.uint64(0xFFFFFFFF)).astype(np.uint32).tobytes(), "base": base, "docs": packed, "twice": several[span].tobytes()})
        return rows

    def run(batches):
        for batch in (part for whole in batches for part in slices(whole, 1, BLOCK_BYTES)):
            ids, n_words, digests, found, seen, size = [], [], [], [], set(), 0
            # by doc_id, so that the copy that stands for others in a block is the one to keep
            for d, text in sorted(zip(column(batch, "doc_id").to_pylist(), texts(batch), strict=True)):
                words = text.split()
                digest = xxhash.xxh3_128_digest(b" ".join(words))
                ids.append(d)
                n_words.append(len(words))
                digests.append(digest)
                if len(words) >= window and digest not in seen:
                    seen.add(digest)
                    grams, least = minimizers(word_hashes(words), window, gram)
                    keys = np.unique(least >> shift)
                    all_, counts = np.unique(grams >> shift, return_counts=True)
                    found.append((len(ids) - 1, keys, counts[np.searchsorted(all_, keys)] > 1))
                    size += len(words)
                if size >= BLOCK_WORDS:
                    yield pa.RecordBatch.from_pylist(block(ids, n_words, digests, found), _SCAN)
                    ids, n_words, digests, found, seen, size = [], [], [], [], set(), 0
            if ids:
                yield pa.RecordBatch.from_pylist(block(ids, n_words, digests, found), _SCAN)

    return docs.select("doc_id", "text").mapInArrow(tidy(run), _SCAN_SQL)


def _repeated_keys(scan: DataFrame) -> DataFrame:
    """doc_id, key for keys that more than one document, or one document twice, has."""

    def count(group: pa.Table) -> pa.Table:
        cols = group.to_pydict()
        key = np.concatenate([np.frombuffer(x, np.uint32) for x in cols["low"]])
        doc = np.concatenate([_ids(b, x) for b, x in zip(cols["base"], cols["docs"], strict=True)])
        twice = np.concatenate([np.frombuffer(x, np.bool_) for x in cols["twice"]])
        order = np.argsort(key, kind="stable")
        key, doc, twice = key[order], doc[order], twice[order]
        at = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        n = np.diff(np.r_[at, len(key)])
        many = np.repeat((n > 1) | np.logical_or.reduceat(twice, at), n) & ~twice
        full = (np.int64(cols["part"][0]) << np.int64(32)) + key[many].astype(np.int64)
        return pa.table({"doc_id": pa.array(doc[many]), "key": pa.array(full)})

    packed = scan.filter("part >= 0").select("part", "low", "base", "docs", "twice")
    return packed.groupBy("part").applyInArrow(count, "doc_id long, key long")


_JUDGE = pa.schema([("kind", pa.int32()), ("part", pa.int32()), ("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string()), ("text", pa.binary()), ("hash", pa.binary()), ("base", pa.int64()), ("docs", pa.binary()), ("starts", pa.binary()), ("a", pa.int64()), ("b", pa.int64())])
_JUDGE_SQL = "kind int, part int, doc_id long, n_words long, n_removed long, kept_sha256 string, text binary, hash binary, base long, docs binary, starts binary, a long, b long"
DONE, OPEN, WINDOWS, SPAN = range(4)


def _runs(starts: np.ndarray, window: int) -> list[tuple[int, int]]:
    """Word spans covered by windows at sorted starts."""
    if not len(starts):
        return []
    at = np.flatnonzero(np.r_[True, np.diff(starts) > window])
    last = np.r_[at[1:], len(starts)] - 1
    return list(zip(starts[at].tolist(), (starts[last] + window).tolist(), strict=True))


def _kept(words: list[bytes], spans: list[tuple[int, int]]) -> tuple[int, list[bytes]]:
    gone = np.zeros(len(words) + 1, np.int32)
    for a, b in spans:
        gone[a] += 1
        gone[b] -= 1
    stay = (np.cumsum(gone)[:-1] == 0).tolist()
    kept = [w for w, s in zip(words, stay, strict=True) if s]
    return len(words) - len(kept), kept


def _judge(joined: DataFrame, window: int, gram: int, bits: int) -> DataFrame:
    shift = np.uint64(64 - 32 - bits)

    def final(doc, words, removed, kept) -> dict:
        return {"kind": DONE, "doc_id": doc, "n_words": len(words), "n_removed": removed, "kept_sha256": hashlib.sha256(b" ".join(kept)).hexdigest()}

    def block(found: list[tuple[int, np.ndarray, np.ndarray, np.ndarray]]) -> list[dict]:
        rows = []
        if not found:
            return rows
        doc = np.repeat(np.array([f[0] for f in found], np.int64), [len(f[1]) for f in found])
        start, key, hashed = (np.concatenate([f[i] for f in found]) for i in (1, 2, 3))
        part = _deal(key, bits)
        order = np.lexsort((start, doc, hashed, part))
        doc, start, hashed, part = doc[order], start[order], hashed[order], part[order]
        later = np.r_[False, (hashed[1:] == hashed[:-1]) & (part[1:] == part[:-1])]
        # an earlier occurrence in this block settles a window; the first one stands for all of them
        order = np.lexsort((start[later], doc[later]))
        for d, span in _split(doc[later][order]):
            rows += [{"kind": SPAN, "doc_id": d, "a": a, "b": b} for a, b in _runs(start[later][order][span], window)]
        doc, start, hashed, part = doc[~later], start[~later], hashed[~later], part[~later]
        order = np.lexsort((start, doc, part))
        doc, start, hashed, part = doc[order], start[order], hashed[order], part[order]
        for p, span in _split(part):
            base, packed = _offsets(doc[span])
            rows.append({"kind": WINDOWS, "part": p, "hash": hashed[span].tobytes(), "base": base, "docs": packed, "starts": start[span].astype(np.uint32).tobytes()})
        return rows

    def run(batches):
        for batch in (part for whole in batches for part in slices(whole, 1, BLOCK_BYTES)):
            rows, found, size = [], [], 0
            cols = {c: column(batch, c).to_pylist() for c in ("doc_id", "first", "keys", "more")}
            for d, text, first, keys, more in zip(cols["doc_id"], texts(batch), cols["first"], cols["keys"], cols["more"], strict=True):
                words = text.split()
                if len(words) < window:
                    rows.append(final(d, words, 0, words))
                elif not first:
                    rows.append(final(d, words, len(words), []))
                else:
                    known = np.unique(np.concatenate([np.frombuffer(keys or b"", np.uint64), np.array(more or [], np.int64).view(np.uint64)]))
                    if len(known):
                        h = word_hashes(words)
                        least = minimizers(h, window, gram)[1] >> shift
                        start = np.flatnonzero(known[np.minimum(np.searchsorted(known, least), len(known) - 1)] == least)
                    if not len(known) or not len(start):
                        rows.append(final(d, words, 0, words))
                        continue
                    rows.append({"kind": OPEN, "doc_id": d, "text": text})
                    found.append((d, start, least[start], rolling(h, window)[start]))
                    size += len(start)
                if size >= BLOCK_WORDS:
                    yield pa.RecordBatch.from_pylist(rows + block(found), _JUDGE)
                    rows, found, size = [], [], 0
            yield pa.RecordBatch.from_pylist(rows + block(found), _JUDGE)

    return joined.mapInArrow(tidy(run), _JUDGE_SQL)


def _spans(judged: DataFrame, window: int) -> DataFrame:
    """doc_id, a, b: word spans of windows that also start earlier."""

    def later(group: pa.Table) -> pa.Table:
        cols = group.to_pydict()
        hashed = np.concatenate([np.frombuffer(x, np.uint64) for x in cols["hash"]])
        doc = np.concatenate([_ids(b, x) for b, x in zip(cols["base"], cols["docs"], strict=True)])
        start = np.concatenate([np.frombuffer(x, np.uint32) for x in cols["starts"]]).astype(np.int64)
        order = np.lexsort((start, doc, hashed))
        doc, start, hashed = doc[order], start[order], hashed[order]
        again = np.r_[False, hashed[1:] == hashed[:-1]]
        doc, start = doc[again], start[again]
        order = np.lexsort((start, doc))
        doc, start = doc[order], start[order]
        at = np.flatnonzero(np.r_[True, (doc[1:] != doc[:-1]) | (start[1:] - start[:-1] > window)]) if len(doc) else np.array([], np.int64)
        last = np.r_[at[1:], len(doc)].astype(np.int64) - 1 if len(doc) else at
        return pa.table({"doc_id": pa.array(doc[at]), "a": pa.array(start[at]), "b": pa.array(start[last] + window if len(doc) else start)})

    packed = judged.filter(F.col("kind") == WINDOWS).select("part", "hash", "base", "docs", "starts")
    return packed.groupBy("part").applyInArrow(later, "doc_id long, a long, b long")


def removal(docs: DataFrame, window: int = 20, gram: int = 10) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 for every row of docs.

    Null texts have no words.  Rows that share a doc_id are ordered by text, equal rows count as one and get
    equal results; a null doc_id orders first.  An empty table gives no rows; other columns are ignored."""
    base, back = unique_ids(docs)
    bits = _ranges(base, gram)
    scan = table(_scan(base, window, gram, bits), "substring-scan")
    info = scan.filter("part = -1").select("doc_id", "digest", "keys", "n_words")
    firsts = info.filter(F.col("n_words") >= window).groupBy("digest").agg(F.min("doc_id").alias("head"))
    meta = info.join(firsts, "digest", "left").select("doc_id", (F.col("doc_id") == F.coalesce("head", "doc_id")).alias("first"), "keys")
    more = _repeated_keys(scan).groupBy("doc_id").agg(F.collect_list("key").alias("more"))
    joined = base.join(meta, "doc_id").join(more, "doc_id", "left").select("doc_id", "text", "first", "keys", "more")
    judged = table(_judge(joined, window, gram, bits), "substring-windows")
    spans = _spans(judged, window).unionByName(judged.filter(F.col("kind") == SPAN).select("doc_id", "a", "b"))
    spans = spans.groupBy("doc_id").agg(F.collect_list(F.struct("a", "b")).alias("spans"))
    left = judged.filter(F.col("kind") == OPEN).select("doc_id", "text").join(spans, "doc_id", "left")

    def finish():
        def step(batch):
            n, removed, sha = [], [], []
            for text, found in zip(texts(batch), column(batch, "spans").to_pylist(), strict=True):
                words = text.split()
                gone, kept = _kept(words, [(s["a"], s["b"]) for s in found or []])
                n.append(len(words))
                removed.append(gone)
                sha.append(hashlib.sha256(b" ".join(kept)).hexdigest())
            return {"doc_id": column(batch, "doc_id"), "n_words": pa.array(n, pa.int64()), "n_removed": pa.array(removed, pa.int64()), "kept_sha256": pa.array(sha, pa.string())}

        return step

    names = ["doc_id", "n_words", "n_removed", "kept_sha256"]
    out = arrow_map(left, finish, "doc_id long, n_words long, n_removed long, kept_sha256 string")
    return back(out.unionByName(judged.filter(F.col("kind") == DONE).select(*names)))
