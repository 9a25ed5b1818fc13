"""Document fingerprints from chains of content words that follow common-word anchors.

A signature is a common word with the two next words that aren't common; a fingerprint is the sorted
multiset of 32-bit signature hashes, 8 hex digits each.  Texts without an anchor chain have one signature, of
all their words (or of the text, where it has none); an empty text has the empty fingerprint.  Likeness is the
Jaccard coefficient of the multisets; two empty fingerprints are alike."""

from __future__ import annotations

import hashlib
from math import log

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_map, column, slices, table, texts, tidy, unique_ids
from .decontam import words_of
from .minhash import resolve
from .substring import word_hashes

# fixed values: common words of English, French, German and Spanish
ANCHORS = frozenset(w.encode() for w in """
a an and are as at be been but by for from had has have he her his i in is it its not of on or she that the their there they this to was we were which who will with you
au aux avec ce ces dans de des du elle en est et il je la le les leur mais ne nous ou par pas pour que qui sa se ses son sur un une vous
auf aus bei das dass dem den der die ein eine einem einen einer er es für hat ich ihr im ist mit nach nicht noch oder sich sie sind um und von war wie wird zu zum zur
al como con del el ella entre era este ha las lo los me mi muy más no nos o para pero por si sin su sus también te todo y ya
""".split())
_K = np.uint64(0x9E3779B97F4A7C15)
_M = np.uint64(0xC2B2AE3D27D4EB4F)


def signatures(text: str, chain: int = 2) -> np.ndarray:
    """Sorted signature hashes, as often as they occur."""
    words = words_of(text.lower().encode())
    if words:
        common = np.fromiter(map(ANCHORS.__contains__, words), np.bool_, len(words))
        content = np.flatnonzero(~common)
        anchor = np.flatnonzero(common)
        follow = np.searchsorted(content, anchor)
        ok = follow + chain <= len(content)
        if ok.any():
            h = word_hashes(words)
            out = h[anchor[ok]]
            for k in range(chain):
                out = (out ^ (out >> np.uint64(31))) * _K + h[content[follow[ok] + k]]
            return np.sort(((out ^ (out >> np.uint64(29))) * _M >> np.uint64(32)).astype(np.uint32))
    elif not text:
        return np.zeros(0, np.uint32)
    whole = b" ".join(words) if words else text.encode()
    return np.array([xxhash.xxh3_64_intdigest(whole) >> 32], np.uint32)


def fingerprint(sigs: np.ndarray) -> str:
    return sigs.astype(">u4").tobytes().hex()


def parse(text: str) -> np.ndarray:
    return np.frombuffer(bytes.fromhex(text), ">u4").astype(np.uint32)


def _numbered(sigs: np.ndarray) -> np.ndarray:
    """The multiset as a set: each signature with its occurrence number."""
    n = np.arange(len(sigs))
    first = np.r_[True, sigs[1:] != sigs[:-1]] if len(sigs) else np.zeros(0, bool)
    return sigs.astype(np.uint64) << np.uint64(32) | (n - np.maximum.accumulate(np.where(first, n, 0))).astype(np.uint64)


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    if not len(a) and not len(b):
        return 1.0
    both = len(np.intersect1d(_numbered(a), _numbered(b), assume_unique=True))
    return both / (len(a) + len(b) - both)


def _edited(text: str, after: str) -> str:
    n = len(text) // 4
    return text[: len(text) - n] + after[:n]


def _cuts(base: DataFrame, part_bytes: int) -> np.ndarray:
    """The first doc_id of each range of about ``part_bytes`` of text, ascending (a longer text is a range with others).

    Ids and sizes alone are sorted; sums of the sorted partitions place each row in the whole.  A number for each
    range comes to the driver, and at most a million: ranges grow beyond a million times ``part_bytes``."""
    spark = base.sparkSession
    sizes = base.select("doc_id", (F.coalesce(F.octet_length("text"), F.lit(0)) + 1).cast("long").alias("size"))
    placed = table(sizes.repartitionByRange("doc_id").withColumn("pid", F.spark_partition_id()), "spots-sizes")
    sums = sorted((r["low"], r["pid"], r["size"]) for r in placed.groupBy("pid").agg(F.min("doc_id").alias("low"), F.sum("size").alias("size")).collect())
    if not sums:
        return np.zeros(0, np.int64)
    total = sum(x[2] for x in sums)
    least = max(1 << 18, total // int(spark.conf.get("spark.sql.shuffle.partitions")))  # enough ranges for all cores
    part_bytes = max(min(part_bytes, least), total // 1_000_000)
    before = np.cumsum([0, *(x[2] for x in sums)])
    offsets = spark.createDataFrame([(pid, int(o)) for (_, pid, _), o in zip(sums, before, strict=False)], "pid int, before long")
    rows = Window.partitionBy("pid").orderBy("doc_id")
    part = F.floor((F.col("before") + F.sum("size").over(rows) - F.col("size")) / part_bytes)
    firsts = placed.join(F.broadcast(offsets), "pid").withColumn("part", part).groupBy("part").agg(F.min("doc_id").alias("doc_id"))
    return np.sort(np.asarray(firsts.select("doc_id").toArrow().column(0)).astype(np.int64))


def neighbours(docs: DataFrame, part_bytes: int = 16 << 20) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next for every row.

    Documents are dealt by ranges of doc_id of about equal bytes, once; each range also gets the first document of
    the range after it.  Null texts count as empty.  Rows that share a doc_id are ordered by text, equal rows count
    as one; a null doc_id orders first.  An empty table gives no rows; other columns are ignored."""
    base, back = unique_ids(docs)
    cuts = _cuts(base, part_bytes)
    parts = max(1, len(cuts))
    shared = docs.sparkSession.sparkContext.broadcast(cuts)

    def deal(batches):
        """Each row with its range, and the first row of a range also, as head, for the range before."""
        for batch in batches:
            ids = np.asarray(column(batch, "doc_id"))
            at = np.searchsorted(shared.value, ids, "right") - 1
            firsts = np.flatnonzero(shared.value[at] == ids)
            rows = np.concatenate([np.arange(len(ids)), firsts])
            own = batch.take(pa.array(rows))
            part = np.concatenate([at, (at[firsts] - 1) % parts]).astype(np.int32)
            head = np.arange(len(rows)) >= len(ids)
            yield pa.RecordBatch.from_arrays([*own.columns, pa.array(part), pa.array(head)], names=[*own.schema.names, "part", "head"])

    rows = base.mapInArrow(tidy(deal), "doc_id long, text string, part int, head boolean").repartitionById(parts, F.col("part")).sortWithinPartitions("head", "doc_id")
    fields = [("doc_id", pa.int64()), ("n_chars", pa.int64()), ("edited_sha256", pa.string()), ("fingerprint", pa.string()), ("edited_fingerprint", pa.string()), ("near_edited", pa.float64()), ("near_next", pa.float64())]

    def run(batches):
        held = None  # the document before
        for batch in (part for whole in batches for part in slices(whole, whole.schema.get_field_index("text"))):
            out = []
            for d, raw, head in zip(column(batch, "doc_id").to_pylist(), texts(batch), column(batch, "head").to_pylist(), strict=True):
                text = raw.decode()
                sigs = signatures(text)
                if held is not None:
                    own_id, own, own_sigs = held
                    changed = _edited(own, text)
                    other = signatures(changed) if changed != own else own_sigs
                    out.append((own_id, len(own), hashlib.sha256(changed.encode()).hexdigest(), fingerprint(own_sigs), fingerprint(other), likeness(own_sigs, other), likeness(own_sigs, sigs)))
                held = d, text, sigs
            cols = list(zip(*out, strict=True)) or [[] for _ in fields]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(cols, fields, strict=True)], names=[n for n, _ in fields])

    return back(rows.mapInArrow(tidy(run), "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"))


def near_classes(docs: DataFrame, percent: int = 80) -> DataFrame:
    """doc_id, class_id: the smallest doc_id reachable over pairs with a likeness of ``percent`` hundredths or more.

    Equal fingerprints are one representative.  Candidates share one of their rarest signatures within one
    or two neighbouring partitions of set length; a pair is compared only if the lengths allow the threshold."""
    base, back = unique_ids(docs)

    def make():
        def step(batch):
            prints = [fingerprint(signatures(t.decode())) for t in texts(batch)]
            return {"doc_id": column(batch, "doc_id"), "print": pa.array(prints, pa.string()), "n": pa.array([len(p) // 8 for p in prints], pa.int64())}

        return step

    prints = table(arrow_map(base, make, "doc_id long, print string, n long"), "spots")
    digest = F.sha2("print", 256)
    groups = prints.groupBy(digest.alias("digest")).agg(F.min("doc_id").alias("rep"))
    placed = table(prints.select("doc_id", digest.alias("digest")).join(groups, "digest").select("doc_id", "rep"), "spots-placed")
    reps = table(prints.join(placed.filter("doc_id = rep").select("doc_id"), "doc_id").filter("n > 0"), "spots-reps")

    def split():
        def step(batch):
            numbered = [_numbered(parse(p)).view(np.int64) for p in column(batch, "print").to_pylist()]
            doc = np.repeat(np.asarray(column(batch, "doc_id")), [len(x) for x in numbered])
            n = np.repeat(np.asarray(column(batch, "n")), [len(x) for x in numbered])
            return {"doc_id": pa.array(doc), "n": pa.array(n), "sig": pa.array(np.concatenate(numbered))}

        return step

    spots = arrow_map(reps, split, "doc_id long, n long, sig long")
    often = spots.groupBy("sig").agg(F.count("*").alias("often"))
    rare = Window.partitionBy("doc_id").orderBy("often", "sig")
    need = F.col("n") - F.ceil(F.col("n") * percent / 100 - 1e-9) + 1
    first = spots.join(often, "sig").withColumn("nth", F.row_number().over(rare)).filter((F.col("nth") <= need) & (F.col("often") > 1))
    step = -log(percent / 100) if percent < 100 else log(2)
    band = F.floor(F.log("n") / F.lit(step)).cast("int")
    keyed = first.select(F.explode(F.array(band, band + 1)).alias("band"), "sig", F.col("doc_id").alias("id")).select(F.xxhash64("band", "sig").alias("key"), "id").distinct()
    buckets = keyed.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1")
    members = table(keyed.join(buckets, "key").select("key", "id", "n"), "spots-members")
    one, two = (reps.select(F.col("doc_id").alias(c), F.col("n").alias(f"n{c}")) for c in "ab")

    def likely(pairs: DataFrame) -> DataFrame:
        fits = 100 * F.least("na", "nb") >= percent * F.greatest("na", "nb")
        return pairs.join(one, "a").join(two, "b").filter(fits).select("a", "b", F.least("na", "nb").cast("int").alias("agree"))

    def items():
        def step(batch):
            data = [np.sort(_numbered(parse(p))).tobytes() for p in column(batch, "print").to_pylist()]
            return {"id": column(batch, "doc_id"), "sig": pa.array([b""] * len(data), pa.binary()), "items": pa.array(data, pa.binary())}

        return step

    signed = table(arrow_map(reps, items, "id long, sig binary, items binary"), "spots-items")
    labels = resolve(members, signed, percent, likely, None).select(F.col("id").alias("rep"), "label")
    out = placed.join(labels, "rep", "left").select("doc_id", F.coalesce("label", "rep").alias("component_id"))
    return back(out).select("doc_id", F.col("component_id").alias("class_id"))
