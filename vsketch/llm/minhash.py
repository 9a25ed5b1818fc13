"""Near-duplicate documents: banded MinHash candidates, sequential Bayesian verification, exact check.

Documents with equal shingle sets are one representative.  In each band bucket members are first paired with
the bucket's center only, the member that shares most buckets with most others; verified pairs are joined into
components.  What is left undecided are pairs of a bucket that lie in different components.  For each bucket
the members outside its commonest component are compared with that component and with one another, in blocks
of a few hundred whose pairs never become rows: a block yields only links that join components.  So no link
between different texts is lost, and rows grow with members.  A candidate is dropped as soon as, after a batch
of signature values, its chance of reaching the threshold falls under the miss probability; the others are
checked on their full sets."""

from __future__ import annotations

from collections.abc import Callable
from math import comb

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, column, table, texts, tidy, unique_ids, without
from .substring import rolling, word_hashes

HASHES = 160
BATCH = 32
MISS = 1e-9
ONE_TASK = 500_000  # links (8 MB) that one task joins into components; more are joined by all tasks
BLOCK_BYTES = 32 << 20  # of items in a block of members, on average
_RNG = np.random.Generator(np.random.PCG64(20240229))
_A = (_RNG.integers(0, 1 << 32, HASHES, np.uint64) | np.uint64(1)).astype(np.uint32)[:, None]
_C = _RNG.integers(0, 1 << 32, HASHES, np.uint64).astype(np.uint32)[:, None]


def shingles(text: bytes, size: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of ``size`` words running; fewer words: of the whole sequence; none: empty."""
    words = text.lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    return np.unique(rolling(word_hashes(words), min(size, len(words))))


def signature(found: np.ndarray) -> np.ndarray:
    out = np.full(HASHES, 0xFFFFFFFF, np.uint32)
    x = (found >> np.uint64(32)).astype(np.uint32)
    for i in range(0, len(x), 2048):
        np.minimum(out, (_A * x[None, i : i + 2048] + _C).min(axis=1), out=out)
    return out


def band_rows(percent: int, miss: float = 1e-6) -> int:
    """The most rows in a band at which pairs at the threshold share no band less often than ``miss``."""
    t = percent / 100
    return max([r for r in range(1, 17) if (1 - t**r) ** (HASHES // r) <= miss], default=1)


def bands(sig: np.ndarray, rows: int) -> np.ndarray:
    n = HASHES // rows
    out = np.arange(1, n + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    for part in sig[: n * rows].reshape(n, rows).astype(np.uint64).T:
        out = (out ^ part) * np.uint64(0xFF51AFD7ED558CCD)
        out ^= out >> np.uint64(31)
    return out.view(np.int64)


def least_matches(percent: int, miss: float = MISS) -> list[int]:
    """After each batch, the fewest matches that leave a chance of at least ``miss`` (uniform prior) of the threshold."""
    t, out = percent / 100, []
    for n in range(BATCH, HASHES + 1, BATCH):
        tail, k = 0.0, -1
        while tail < miss and k < n:
            k += 1
            tail += comb(n + 1, k) * t**k * (1 - t) ** (n + 1 - k)
        out.append(k)
    return out


def _digest(found: np.ndarray) -> bytes:
    with np.errstate(over="ignore"):
        return np.array([found.sum(dtype=np.uint64), np.bitwise_xor.reduce(found * np.uint64(0xC2B2AE3D27D4EB4F) >> np.uint64(3)) if len(found) else 0], np.uint64).tobytes()


def _scan(docs: DataFrame, size: int, rows: int) -> DataFrame:
    def make():
        def step(batch):
            n, digest, keys = [], [], []
            for text in texts(batch):
                found = shingles(text, size)
                n.append(len(found))
                digest.append(_digest(found))
                keys.append(bands(signature(found), rows) if len(found) else np.zeros(0, np.int64))
            ends = np.cumsum([0, *map(len, keys)], dtype=np.int32)
            return {"doc_id": column(batch, "doc_id"), "n_shingles": pa.array(n, pa.int64()), "digest": pa.array(digest, pa.binary()), "bands": pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(keys)))}

        return step

    return arrow_map(docs, make, "doc_id long, n_shingles long, digest binary, bands array<long>", "text")


def _signed(docs: DataFrame, size: int) -> DataFrame:
    """id, sig, items (sorted 64-bit shingle hashes)."""

    def make():
        def step(batch):
            found = [shingles(t, size) for t in texts(batch)]
            return {"id": column(batch, "doc_id"), "sig": pa.array([signature(x).tobytes() for x in found], pa.binary()), "items": pa.array([x.tobytes() for x in found], pa.binary())}

        return step

    return arrow_map(docs, make, "id long, sig binary, items binary", "text")


def _likely(pairs: DataFrame, signed: DataFrame, percent: int, miss: float) -> DataFrame:
    """a, b, agree for pairs that no batch of signature values rules out."""
    need = least_matches(percent, miss)
    sig = signed.select("id", "sig")
    both = pairs.join(sig.select(F.col("id").alias("b"), F.col("sig").alias("sig_b")), "b").join(sig.select(F.col("id").alias("a"), F.col("sig").alias("sig_a")), "a")

    def make():
        def step(batch):
            one, two = (np.frombuffer(b"".join(column(batch, c).to_pylist()), np.uint32).reshape(-1, HASHES) for c in ("sig_a", "sig_b"))
            alive, agree = np.arange(len(one)), np.zeros(len(one), np.int32)
            for k, least in enumerate(need):
                span = slice(k * BATCH, (k + 1) * BATCH)
                agree[alive] += (one[alive, span] == two[alive, span]).sum(axis=1).astype(np.int32)
                alive = alive[agree[alive] >= least]
            take = pa.array(alive)
            return {"a": column(batch, "a").take(take), "b": column(batch, "b").take(take), "agree": pa.array(agree[alive])}

        return step

    return arrow_map(both.select("a", "b", "sig_a", "sig_b"), make, "a long, b long, agree int")


def _linked(pairs: DataFrame, signed: DataFrame, percent: int) -> DataFrame:
    """Pairs whose full sets reach the threshold."""
    items = signed.select("id", "items")
    both = pairs.select("a", "b").join(items.select(F.col("id").alias("b"), F.col("items").alias("items_b")), "b").join(items.select(F.col("id").alias("a"), F.col("items").alias("items_a")), "a")

    def make():
        def step(batch):
            keep = [_alike(np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64), percent) for x, y in zip(column(batch, "items_a").to_pylist(), column(batch, "items_b").to_pylist(), strict=True)]
            kept = pa.array(np.flatnonzero(keep))
            return {"a": column(batch, "a").take(kept), "b": column(batch, "b").take(kept)}

        return step

    return arrow_map(both.select("a", "b", "items_a", "items_b"), make, "a long, b long")


def _alike(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    if 100 * min(len(a), len(b)) < percent * max(len(a), len(b)):
        return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both)


def _shared(one: list[np.ndarray], two: list[np.ndarray], width: int = 4096) -> np.ndarray:
    """Sizes of all intersections of two lists of sets, by matrix products over stretches of the items."""
    every = np.unique(np.concatenate(one))
    out = np.zeros((len(one), len(two)), np.float32)

    def places(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        flat, row = np.concatenate(sets), np.repeat(np.arange(len(sets)), [len(x) for x in sets])
        at = np.minimum(np.searchsorted(every, flat), len(every) - 1)
        ok = every[at] == flat
        at, row = at[ok], row[ok]
        order = np.argsort(at, kind="stable")
        return at[order], row[order]

    (at_1, row_1), (at_2, row_2) = places(one), places(two)
    for lo in range(0, len(every), width):
        parts = []
        for at, row, n in ((at_1, row_1, len(one)), (at_2, row_2, len(two))):
            span = slice(np.searchsorted(at, lo), np.searchsorted(at, lo + width))
            m = np.zeros((n, width), np.float32)
            m[row[span], at[span] - lo] = 1
            parts.append(m)
        out += parts[0] @ parts[1].T
    return out


def _block_links(one: list[dict], two: list[dict], percent: int, need: list[int] | None) -> list[tuple[int, int]]:
    """Links between two blocks that join different labels; at most one less than there are labels."""
    id_1, id_2 = (np.array([r["id"] for r in x], np.int64) for x in (one, two))
    label_1, label_2 = (np.array([r["label"] for r in x], np.int64) for x in (one, two))
    both_ways = np.array([r["odd"] for r in two])
    alive = (label_1[:, None] != label_2[None, :]) & ~(both_ways[None, :] & (id_2[None, :] <= id_1[:, None]))
    if need is not None and alive.any():
        sig_1, sig_2 = (np.frombuffer(b"".join(r["sig"] for r in x), np.uint32).reshape(-1, HASHES) for x in (one, two))
        agree = np.zeros(alive.shape, np.int32)
        for k, least in enumerate(need):
            span = slice(k * BATCH, (k + 1) * BATCH)
            rows = np.flatnonzero(alive.any(1))
            for i in rows:
                agree[i] += (sig_2[:, span] == sig_1[i, span]).sum(1)
            alive &= agree >= least
            if not alive.any():
                return []
    if not alive.any():
        return []
    set_1, set_2 = ([np.frombuffer(r["items"], np.uint64) for r in x] for x in (one, two))
    n_1, n_2 = np.array([len(x) for x in set_1]), np.array([len(x) for x in set_2])
    rows, cols = np.flatnonzero(alive.any(1)), np.flatnonzero(alive.any(0))
    if alive.sum() <= 64:
        hit = [(i, j) for i, j in np.argwhere(alive) if _alike(set_1[i], set_2[j], percent)]
    else:
        both = np.rint(_shared([set_1[i] for i in rows], [set_2[j] for j in cols])).astype(np.int64)
        ok = (100 * both >= percent * (n_1[rows][:, None] + n_2[cols][None, :] - both)) & alive[np.ix_(rows, cols)]
        hit = [(rows[i], cols[j]) for i, j in np.argwhere(ok)]
    root: dict[int, int] = {}

    def top(x: int) -> int:
        while root.get(x, x) != x:
            x = root[x] = root.get(root[x], root[x])
        return x

    out = []
    for i, j in hit:
        p, q = top(int(label_1[i])), top(int(label_2[j]))
        if p != q:
            root[max(p, q)] = min(p, q)
            out.append((int(id_1[i]), int(id_2[j])))
    return out


def _rest_links(members: DataFrame, labels: DataFrame, signed: DataFrame, percent: int, need: list[int] | None, block: int = 192) -> DataFrame:
    """Links among members of a bucket (key, id) that lie in different components."""
    named = members.join(labels, "id", "left").select("key", "id", F.coalesce("label", "id").alias("label"))
    counts = named.groupBy("key", "label").agg(F.count("*").alias("n"))
    mixed = counts.groupBy("key").agg(F.max_by("label", F.struct("n", "label")).alias("main"), F.count("*").alias("labels")).filter("labels > 1").select("key", "main")
    odd = table(named.join(mixed, "key").filter("label <> main").select("main", "id", "label").distinct(), "near-odd")
    mains = odd.select("main").distinct()
    ids = members.select("id").distinct().join(labels, "id", "left").select("id", F.coalesce("label", "id").alias("main"))
    home = ids.join(mains, "main").select("main", "id", F.col("main").alias("label"), F.lit(False).alias("odd"))
    group = home.unionByName(odd.withColumn("odd", F.lit(True)))
    weights = signed.select("id", F.length("items").alias("width"))
    by_count, by_bytes = F.ceil(F.count("*") / block), F.ceil(F.sum(F.coalesce("width", F.lit(0))) / BLOCK_BYTES)
    sizes = group.join(weights, "id", "left").groupBy("main").agg(F.greatest(by_count, by_bytes).cast("long").alias("blocks"))
    placed = group.join(sizes, "main").withColumn("part", F.pmod(F.xxhash64("id"), F.col("blocks"))).join(signed, "id")
    content = F.collect_list(F.struct("id", "label", "odd", "sig", "items"))
    every = placed.groupBy("main", "part").agg(content.alias("two"))
    some = placed.filter("odd").select("main", "part", "blocks", "id", "label", "odd", "sig", "items").groupBy("main", "part", "blocks").agg(content.alias("one"))
    some = some.select("main", "one", F.explode(F.expr("sequence(0L, blocks - 1)")).alias("part"))  # blocks: a 192nd of the members, more for very long texts
    both = some.join(every, ["main", "part"]).select("one", "two")

    def make():
        def step(batch):
            links = [x for one, two in zip(column(batch, "one").to_pylist(), column(batch, "two").to_pylist(), strict=True) for x in _block_links(one, two, percent, need)]
            return {"a": pa.array([x[0] for x in links], pa.int64()), "b": pa.array([x[1] for x in links], pa.int64())}

        return step

    return arrow_map(both, make, "a long, b long")


def _roots_at_once(edges: DataFrame) -> DataFrame:
    """a, root for labels that are not their component's smallest; for up to ONE_TASK edges, in one task."""

    def run(batches):
        up: dict[int, int] = {}

        def top(x: int) -> int:
            while (above := up.get(x, x)) != x:
                up[x] = up.get(above, above)
                x = above
            return x

        for batch in batches:
            for a, b in zip(column(batch, "a").to_pylist(), column(batch, "b").to_pylist(), strict=True):
                a, b = top(a), top(b)
                if a != b:
                    up[max(a, b)] = min(a, b)
        low = list(up)
        if low:
            yield pa.RecordBatch.from_arrays([pa.array(low, pa.int64()), pa.array([top(x) for x in low], pa.int64())], names=["a", "root"])

    return edges.select("a", "b").coalesce(1).mapInArrow(tidy(run), "a long, root long")


def components(links: DataFrame, labels: DataFrame | None = None) -> DataFrame:
    """id, label (smallest id reachable) of all ends of links and ids of labels; links join whole labels.

    Up to ONE_TASK links between labels are joined in one task.  Beyond that each label hooks to its smallest
    neighbour and chains are shortened by pointer jumping, until so few links cross or none does."""
    edges = links
    if labels is None:
        labels = links.select(F.explode(F.array("a", "b")).alias("id")).distinct().select("id", F.col("id").alias("label"))
    else:
        one, two = (labels.select(F.col("id").alias(c), F.col("label").alias(f"l{c}")) for c in "ab")
        edges = links.join(one, "a", "left").join(two, "b", "left").select(F.coalesce("la", "a").alias("a"), F.coalesce("lb", "b").alias("b"))
        fresh = links.select(F.explode(F.array("a", "b")).alias("id")).distinct().join(labels, "id", "left_anti").select("id", F.col("id").alias("label"))
        labels = labels.unionByName(fresh)
    labels = table(labels, "labels")
    while True:
        edges = table(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a <> b"), "edges")
        few = edges.count() <= ONE_TASK
        roots = table(_roots_at_once(edges) if few else edges.groupBy("a").agg(F.min("b").alias("root")), "roots")
        if roots.isEmpty():
            return labels
        while not few:
            up = roots.select(F.col("a").alias("root"), F.col("root").alias("above"))
            jumped = table(roots.join(up, "root", "left").select("a", F.coalesce("above", "root").alias("root"), F.col("above").isNotNull().alias("moved")), "roots")
            roots = jumped.select("a", "root")
            if jumped.filter("moved").isEmpty():
                break
        by = roots.select(F.col("a").alias("label"), "root")
        labels = table(labels.join(by, "label", "left").select("id", F.coalesce("root", "label").alias("label")), "labels")
        if few:
            return labels
        one, two = (roots.select(F.col("a").alias(c), F.col("root").alias(f"r{c}")) for c in "ab")
        edges = edges.join(one, "a", "left").join(two, "b", "left").select(F.coalesce("ra", "a").alias("a"), F.coalesce("rb", "b").alias("b")).distinct()


def _crossing(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    one, two = (labels.select(F.col("id").alias(c), F.col("label").alias(f"l{c}")) for c in "ab")
    return pairs.join(one, "a", "left").join(two, "b", "left").filter(F.coalesce("la", "a") != F.coalesce("lb", "b")).select(*pairs.columns)


def resolve(members: DataFrame, signed: DataFrame, percent: int, likely_of: Callable[[DataFrame], DataFrame], need: list[int] | None) -> DataFrame:
    """id, label for members of buckets that are joined by links between members of one bucket.

    members: key, id, n (members of the bucket).  signed: id, sig, items.  likely_of keeps pairs a, b that may be
    linked and adds agree (larger for likelier pairs); need: least agreement of signatures after each batch."""
    scores = members.groupBy("id").agg(F.sum("n").alias("score"))
    centers = members.join(scores, "id").groupBy("key").agg(F.max_by("id", F.struct("score", -F.col("id"))).alias("center"))
    members = table(members.select("key", "id").join(centers, "key"), "near-members").filter("id <> center")
    pairs = members.select(F.col("center").alias("a"), F.col("id").alias("b")).distinct()
    likely = table(likely_of(pairs), "near-likely")
    best = likely.groupBy("b").agg(F.max_by("a", F.struct("agree", -F.col("a"))).alias("a"))
    labels = components(table(_linked(best, signed, percent), "near-links"))
    rest = _crossing(likely.select("a", "b"), labels)
    links = table(_linked(rest, signed, percent), "near-links")
    if not links.isEmpty():
        labels = components(links, labels)
    links = table(_rest_links(members.select("key", "id"), labels, signed, percent, need), "near-links")
    return labels if links.isEmpty() else components(links, labels)


def near_duplicates(docs: DataFrame, size: int = 3, percent: int = 85, miss: float = MISS) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row of docs.

    Texts without words (null, empty) have no shingles and no links.  Equal rows share their result; rows
    that share a doc_id are told apart by text; a null doc_id orders first.  An empty table gives no rows;
    other columns are ignored."""
    base, back = unique_ids(docs)
    rows = band_rows(percent)
    scan = table(_scan(base, size, rows), "minhash-scan")
    some = scan.filter("n_shingles > 0")
    groups = some.groupBy("digest").agg(F.min("doc_id").alias("rep"))
    placed = table(some.select("doc_id", "digest").join(groups, "digest").select("doc_id", "rep"), "minhash-placed")
    reps = placed.filter("doc_id = rep").select("doc_id")
    rows_of = some.select("doc_id", "bands").join(reps, "doc_id").select(F.explode("bands").alias("key"), F.col("doc_id").alias("id"))
    buckets = rows_of.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1")
    members = table(rows_of.join(buckets, "key").select("key", "id", "n"), "minhash-members")
    involved = members.select(F.col("id").alias("doc_id")).distinct()
    signed = table(_signed(base.join(involved, "doc_id"), size), "minhash-signed")
    labels = resolve(members, signed, percent, lambda pairs: _likely(pairs, signed, percent, miss), least_matches(percent, miss))
    out = scan.select("doc_id", "n_shingles").join(placed, "doc_id", "left").join(labels.select(F.col("id").alias("rep"), "label"), "rep", "left")
    out = out.select("doc_id", "n_shingles", F.coalesce("label", "rep", "doc_id").alias("component_id"))
    return back(out).select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))


def keep_first(docs: DataFrame, size: int = 5, percent: int = 80) -> DataFrame:
    """Rows of docs, all columns: of each component of near-duplicates the row with the smallest doc_id.

    Texts without words have no links and stay.  Where doc_id is null or repeats, rows that agree in doc_id
    and text become one, and of rows with one doc_id the smaller text goes first."""
    if not docs.groupBy("doc_id").count().filter("count > 1 or doc_id is null").take(1):
        return without(docs, near_duplicates(docs, size, percent).filter("not kept").select("doc_id"))
    columns = docs.columns
    rows = docs.dropDuplicates(["doc_id", "text"]).orderBy(F.col("doc_id").asc_nulls_first(), F.col("text").asc_nulls_first())
    own = next(c for k in range(len(columns) + 1) if (c := f"own_row_{k}") not in columns)
    rows = table(rows.withColumn(own, F.monotonically_increasing_id()), "rows")
    found = near_duplicates(rows.select(F.col(own).alias("doc_id"), "text"), size, percent)
    return without(rows, found.filter("not kept").select(F.col("doc_id").alias(own)), own).select(*columns)
