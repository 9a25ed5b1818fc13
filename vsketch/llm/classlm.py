"""Class-based bigram language model: exchange clustering of words, class transitions, word emissions.

The commonest words are units on their own and all others are first pooled in groups by spelling; exchange clustering
of these ``words`` + ``groups`` units runs until no unit moves.  Then every other word that training holds twice or
more gets the class of the highest likelihood of its own contexts, counted for each word in Spark; only words seen
once, or never, keep the class of their spelling group.  Class transitions are counted again with these classes, over
every training text.  The emission of a word in its class is its smoothed unigram share of the class, so a text's
score is its unigram score plus a sum over class transitions.  The ``table_words`` commonest words of up to 64 bytes,
their counts and classes are broadcast (a fixed bound); counts and classes of all others are joined by word."""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass
from itertools import repeat
from zlib import crc32

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, column, table, texts, tidy

END_WORD = ""  # no word is empty
WORD_BYTES = 64  # longer words are never in the broadcast table but joined by word, with the same counts and classes


def tokens(text: bytes) -> list[bytes]:
    return text.lower().split()


def held_out(doc_id) -> F.Column:
    return (F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))) % 5) == 1


def word_counts(docs: DataFrame) -> DataFrame:
    """word, n over all texts; the end of a text counts under the empty word."""

    def make():
        def step(batch):
            seen: Counter[bytes] = Counter()
            for text in texts(batch):
                seen.update(tokens(text))
            seen[b""] = batch.num_rows
            return {"word": pa.array(list(seen), pa.binary()).cast(pa.string()), "n": pa.array(list(seen.values()), pa.int64())}

        return step

    return arrow_map(docs.select("text"), make, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))


class Units:
    """Units of words: 0 the end, then common words, then spelling groups."""

    def __init__(self, known: list[bytes], words: int, groups: int):
        self.place = {w: i for i, w in enumerate(known)}
        self.words, self.groups = min(words, len(known)), groups
        self.size = 1 + self.words + groups
        self.unit_of = np.array([1 + i if i < self.words else self.spelled(w) for i, w in enumerate(known)], np.int64)

    def spelled(self, word: bytes) -> int:
        return 1 + self.words + crc32(word[-3:]) % self.groups

    def read(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray, list[bytes]]:
        """Places in the table (-1: not there), units, and words that are not there."""
        at = np.fromiter(map(self.place.get, words, repeat(-1)), np.int64, len(words))
        rest = [words[i] for i in np.flatnonzero(at < 0).tolist()]
        unit = self.unit_of[at] if len(self.unit_of) else np.zeros(len(words), np.int64)
        if rest:
            unit[at < 0] = 1 + self.words + np.fromiter((crc32(w[-3:]) for w in rest), np.int64, len(rest)) % self.groups
        return at, unit, rest


END = np.iinfo(np.int32).min


def encode(docs: DataFrame, units) -> DataFrame:
    """row, doc_id, train, ids, rest for each row of docs: the place of each word in the table, or -1 - g for a word
    of spelling group g that is not there; these words stand in rest, in order.  row is unique.  ids are packed, four
    bytes each, so that they are copied and not read one by one wherever a row passes."""

    def make():
        own = units.value

        def step(batch):
            words, ends = [], [0]
            for text in texts(batch):
                words += tokens(text)
                ends.append(len(words))
            at, unit, rest = own.read(words)
            ids = np.where(at < 0, own.words - unit, at).astype(np.int32)
            ends = np.array(ends)
            rest_ends = np.r_[0, np.cumsum(at < 0)][ends].astype(np.int32)
            packed = pa.Array.from_buffers(pa.binary(), len(ends) - 1, [None, pa.py_buffer((4 * ends).astype(np.int32)), pa.py_buffer(ids)])
            return {
                "row": column(batch, "row"), "doc_id": column(batch, "doc_id"), "train": column(batch, "train"), "ids": packed,
                "rest": pa.ListArray.from_arrays(pa.array(rest_ends), pa.array(rest, pa.binary()).cast(pa.string())),
            }

        return step

    rows = docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", "text", (~held_out(F.col("doc_id"))).alias("train"))
    return table(arrow_map(rows, make, "row long, doc_id long, train boolean, ids binary, rest array<string>", slice_by="text"), "lm-ids")


def chain(batch) -> tuple[np.ndarray, np.ndarray]:
    """Ids of the batch's texts in one row, END before, between and after them, and the index of each text's END."""
    ids = column(batch, "ids")
    _, offsets, data = ids.buffers()
    own = np.frombuffer(offsets, np.int32)[ids.offset : ids.offset + len(ids) + 1]
    data = np.frombuffer(data or b"", np.uint8)[own[0] : own[-1]].view(np.int32)
    ends = np.cumsum(np.diff(own) // 4 + 1)
    flat = np.full(ends[-1] + 1, END, np.int64)
    inside = np.ones(len(flat), bool)
    inside[0] = inside[ends] = False
    flat[inside] = data
    return flat, ends


def looked_up(flat: np.ndarray, of_table: np.ndarray, of_group: np.ndarray, end: int) -> np.ndarray:
    """A value of each id: by place in the table, by spelling group, or end."""
    out = np.full(len(flat), end, np.int64)
    known, rare = flat >= 0, (flat < 0) & (flat != END)
    out[known] = of_table[flat[known]]
    out[rare] = of_group[-1 - flat[rare]]
    return out


def pair_counts(encoded: DataFrame, model) -> DataFrame:
    """key, n: how often value b follows value a, key = a * size + b; a text starts and ends at value 0.

    model: broadcast size, values of the table's words and of the groups; pairs with a negative value are left out."""

    def make():
        size, of_table, of_group = model.value

        def step(batch):
            flat, _ = chain(batch)
            value = looked_up(flat, of_table, of_group, 0)
            before, after = value[:-1], value[1:]
            held = (before >= 0) & (after >= 0)
            key, n = np.unique(before[held] * size + after[held], return_counts=True)
            return {"key": pa.array(key.astype(np.int32)), "n": pa.array(n.astype(np.int64))}

        return step

    return arrow_map(encoded.select("ids"), make, "key int, n long").groupBy("key").agg(F.sum("n").alias("n"))


def contexts(encoded: DataFrame, model, head: int) -> tuple[DataFrame, DataFrame]:
    """(word, near) of the table's words after the first ``head``, by place, and of all words beyond the table:
    how often each class stands before the word (key = class) and after it (key = classes + class), count * 2 * classes + key.
    A word has a row for each batch that holds it."""

    size = 2 * model.value[0]

    def packed(word, key):
        """Word number and its contexts (count * size + key), one row a word."""
        found, n = np.unique(word * size + key, return_counts=True)
        word, first = np.unique(found // size, return_index=True)
        return word, pa.ListArray.from_arrays(pa.array(np.r_[first, len(found)].astype(np.int32)), pa.array(n * size + found % size))

    def around(home, at):
        return np.concatenate([home[at - 1], size // 2 + home[at + 1]])

    def of_table():
        _, own, groups = model.value

        def step(batch):
            flat, _ = chain(batch)
            at = np.flatnonzero(flat >= head)
            word, near = packed(np.tile(flat[at], 2), around(looked_up(flat, own, groups, 0), at))
            return {"word": pa.array(word), "near": near}

        return step

    def beyond():
        _, own, groups = model.value

        def step(batch):
            flat, _ = chain(batch)
            at = np.flatnonzero((flat < 0) & (flat != END))
            words = column(batch, "rest").flatten().dictionary_encode()
            word, near = packed(np.tile(np.asarray(words.indices).astype(np.int64), 2), around(looked_up(flat, own, groups, 0), at))
            return {"word": words.dictionary.take(pa.array(word)), "near": near}

        return step

    def near(make, kind, *cols):
        return arrow_map(encoded.select(*cols), make, f"word {kind}, near array<long>")

    return near(of_table, "long", "ids"), near(beyond, "string", "ids", "rest")


def by_key(frame: DataFrame, key: str, run, schema: str) -> DataFrame:
    """run over the batches of a task, where rows of a key stand together.  A sort moves rows as they are, where
    collected lists would be built, and sorted, value by value."""
    return frame.repartition(key).sortWithinPartitions(key).mapInArrow(tidy(run), schema)


def run_starts(key: pa.Array) -> np.ndarray:
    """Where runs of equal values start."""
    return np.r_[0, 1 + np.flatnonzero(np.asarray(pc.not_equal(key.slice(1), key.slice(0, len(key) - 1))))].astype(np.int64)


def summed(batches, classes: int):
    """Words and their contexts as a row of counts (before: classes, after: classes), from batches in order of words."""
    last, over = None, None
    for batch in batches:
        if not batch.num_rows:
            continue
        word, near = column(batch, "word"), column(batch, "near")
        starts = run_starts(word)
        code = np.asarray(near.flatten())
        of = np.repeat(np.searchsorted(starts, np.arange(len(word)), "right") - 1, np.diff(np.asarray(near.offsets)))
        held = np.bincount(of * (2 * classes) + code % (2 * classes), code // (2 * classes), len(starts) * 2 * classes).reshape(-1, 2 * classes)
        words = word.take(pa.array(starts))
        if last is not None and last[0].equals(words[0]):
            held[0] += over[0]
        elif last is not None:
            yield last, over
        if len(words) > 1:
            yield words.slice(0, len(words) - 1), held[:-1]
        last, over = words.slice(len(words) - 1), held[-1:]
    if last is not None:
        yield last, over


def whole(batches, key: str):
    """The same rows, from batches in order of the key, with all rows of a key in one batch."""
    held = []
    join = lambda parts: pa.Table.from_batches(parts).combine_chunks().to_batches()[0]
    for batch in batches:
        if not batch.num_rows:
            continue
        if held and not column(held[0], key)[0].equals(column(batch, key)[0]):
            yield join(held)
            held = []
        last = int(run_starts(column(batch, key))[-1])
        if last:
            yield join([*held, batch.slice(0, last)])
            held = []
        held.append(batch.slice(last))
    if held:
        yield join(held)


def likeliest(held: np.ndarray, gain: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Count of each word and the class of the highest likelihood of what stands around it; class 0 is the end's."""
    classes = len(gain)
    value = held[:, :classes] @ gain + held[:, classes:] @ gain.T
    return held[:, :classes].sum(1).astype(np.int64), 1 + value[:, 1:].argmax(1)


def _f(x: np.ndarray) -> np.ndarray:
    return x * np.log(np.maximum(x, 1.0))


def exchange(pairs: np.ndarray, classes: int) -> np.ndarray:
    """Class of each unit: moves one unit at a time to the class of the highest likelihood, until none moves.

    pairs: units x units counts.  Unit 0, the end of a text, keeps class 0 to itself."""
    n_units = len(pairs)
    weight = pairs.sum(0) + pairs.sum(1)
    order = np.argsort(-weight[1:], kind="stable") + 1
    home = np.zeros(n_units, np.int64)
    home[order] = 1 + np.arange(len(order)) % (classes - 1)
    onehot = np.zeros((n_units, classes))
    onehot[np.arange(n_units), home] = 1
    right, left = (pairs @ onehot, pairs.T @ onehot)  # counts of each unit before and after each class
    both = onehot.T @ right
    least = 1e-9 + 1e-12 * float(_f(pairs.sum()))  # beyond rounding
    moved = 1
    while moved:  # each move raises the likelihood, so it ends
        moved = 0
        for u in order[weight[order] > 0]:
            a, self_pair = home[u], float(pairs[u, u])
            r, s = right[u].copy(), left[u].copy()
            r[a] -= self_pair
            s[a] -= self_pair
            rest = both.copy()
            rest[a] -= r
            rest[:, a] -= s
            rest[a, a] -= self_pair
            flat = _f(rest)
            grown_r, grown_s = _f(rest + r[None, :]) - flat, _f(rest + s[:, None]) - flat
            diag = np.diagonal(rest)
            gain = grown_r.sum(1) - np.diagonal(grown_r) + grown_s.sum(0) - np.diagonal(grown_s) + _f(diag + r + s + self_pair) - _f(diag)
            before, after = rest.sum(1) + s, rest.sum(0) + r  # what stands before or after u counts wherever u goes
            gain -= _f(before + r.sum() + self_pair) - _f(before) + _f(after + s.sum() + self_pair) - _f(after)
            gain[0] = -np.inf
            b = int(np.argmax(gain))
            if b == a or gain[b] <= gain[a] + least:
                continue
            moved += 1
            rest[b] += r
            rest[:, b] += s
            rest[b, b] += self_pair
            both, home[u] = rest, b
            right[:, a] -= pairs[:, u]
            right[:, b] += pairs[:, u]
            left[:, a] -= pairs[u]
            left[:, b] += pairs[u]
    return home


def counted(pairs: DataFrame, size: int) -> np.ndarray:
    got = pairs.toArrow()
    out = np.zeros(size * size)
    out[np.asarray(got.column("key"))] = np.asarray(got.column("n"))
    return out.reshape(size, size)


def gains(moves: np.ndarray, share: np.ndarray, pull: float, blend: float) -> np.ndarray:
    """Log of how much likelier a class is after a class than by itself."""
    step_p = (moves + pull * share[None, :]) / (moves.sum(1, keepdims=True) + pull)
    return np.log10((1 - blend) * step_p / share[None, :] + blend)


def rare_links(encoded: DataFrame, rare: DataFrame, model, norm: float) -> DataFrame:
    """row, train, keys, rest, rest_known of each text with words beyond the table: its class transitions into and
    out of them (class * classes + next class), their base score, and how many training holds."""

    base = model.value[0] + 1

    def make():
        _, own, groups = model.value

        def step(batch):
            flat, ends = chain(batch)
            home = looked_up(flat, own, np.full(len(groups), -1), 0)
            at = np.flatnonzero((flat < 0) & (flat != END))
            doc = 2 * np.asarray(column(batch, "row")) + np.asarray(column(batch, "train")).astype(np.int64)
            mark = ((at * base + groups[-1 - flat[at]]) * base + home[at - 1] + 1) * base + home[at + 1] + 1  # place, own group's class, classes before and after
            return {"doc": pa.array(doc[np.searchsorted(ends, at)]), "word": column(batch, "rest").flatten(), "mark": pa.array(mark)}

        return step

    def link(batches):
        for batch in whole(batches, "doc"):
            docs, mark, own, n = (np.asarray(column(batch, k)).astype(np.int64) for k in ("doc", "mark", "class", "n"))
            doc, text = np.unique(docs, return_inverse=True)
            order = np.lexsort((mark, text))
            text, mark, own, n = text[order], mark[order], own[order], n[order]
            own = np.where(own < 0, mark // base**2 % base, own)  # not in training
            before, after = mark // base % base - 1, mark % base - 1
            before = np.where(before < 0, np.r_[0, own[:-1]], before)  # the word before is also beyond the table
            out = after >= 0
            key, of = np.r_[before * (base - 1) + own, (own * (base - 1) + after)[out]], np.r_[text, text[out]]
            ends = np.r_[0, np.cumsum(np.bincount(of, minlength=len(doc)))].astype(np.int32)
            keys = pa.ListArray.from_arrays(pa.array(ends), pa.array(key[np.argsort(of, kind="stable")].astype(np.int32)))
            rest = np.bincount(text, np.log10((n + 0.5) / norm), len(doc))
            rows = [pa.array(doc // 2), pa.array(doc % 2 == 1), keys, pa.array(rest), pa.array(np.bincount(text[n > 0], minlength=len(doc)))]
            yield pa.RecordBatch.from_arrays(rows, names=["row", "train", "keys", "rest", "rest_known"])

    rows = arrow_map(encoded.select("row", "train", "ids", "rest"), make, "doc long, word string, mark long")
    rows = rows.join(rare, "word", "left").select("doc", "mark", F.coalesce("class", F.lit(-1)).alias("class"), F.coalesce("n", F.lit(0)).alias("n"))
    return by_key(rows, "doc", link, "row long, train boolean, keys array<int>, rest double, rest_known long")


@dataclass
class Fitted:
    """A model and the encoded texts.  Words of the table by place: names, counts, classes; those beyond it in ``rare``
    (word, n, class); unseen words have the class of their spelling group, class 0 is the end's.  ``gain``: log10 of how
    much likelier a class is after a class than by itself, so that log10 P(word | class before) is the base score of the
    word and the gain of its class."""

    units: Units
    n_known: np.ndarray
    n_end: int
    total: int
    norm: float
    of_table: np.ndarray
    of_group: np.ndarray
    rare: DataFrame
    gain: np.ndarray
    encoded: DataFrame
    links: DataFrame


def fit(docs: DataFrame, classes: int = 48, words: int = 1500, groups: int = 300, table_words: int = 100_000, pull: float = 5.0, blend: float = 0.03) -> Fitted:
    """Learns from the rows of docs that are not held out; see score."""
    original = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    spark = docs.sparkSession
    counts = table(word_counts(original.filter(~held_out(F.col("doc_id")))), "lm-words")
    total, types = (x or 0 for x in counts.agg(F.sum("n"), F.count("*")).first())
    norm = total + 0.5 * (types + 1)
    known = counts.filter((F.col("word") != END_WORD) & (F.octet_length("word") <= WORD_BYTES)).orderBy(F.desc("n"), "word").limit(table_words).toArrow()  # a fixed bound
    ends = counts.filter(F.col("word") == END_WORD).select("n").first()
    n_end = ends[0] if ends else 0
    names, n_known = known.column("word").cast(pa.binary()).to_pylist(), np.asarray(known.column("n")).astype(np.int64)
    units = Units(names, words, groups)
    encoded = encode(original, spark.sparkContext.broadcast(units))
    train = encoded.filter("train")

    size = units.size
    by_unit = spark.sparkContext.broadcast((size, units.unit_of, 1 + units.words + np.arange(groups)))
    pairs = counted(pair_counts(train, by_unit), size)  # at most size * size rows of 12 bytes, at any input
    home = exchange(pairs, classes)
    of_group = home[1 + units.words :]
    of_table = home[units.unit_of]
    onehot = (home[:, None] == np.arange(classes)[None, :]).astype(np.float64)
    mass = pairs.sum(1)
    share = np.maximum(np.bincount(home, mass, classes) / max(mass.sum(), 1.0), 1e-12)
    gain = gains(onehot.T @ (pairs @ onehot), share, pull, blend)
    del pairs

    near_table, near_rest = contexts(train, spark.sparkContext.broadcast((classes, of_table, of_group)), units.words)
    shared = spark.sparkContext.broadcast((gain, units.groups, of_group))

    def choose(beyond: bool):
        def run(batches):
            gain, groups, of_group = shared.value
            for word, held in summed(batches, len(gain)):
                n, best = likeliest(held, gain)
                if beyond:  # in the table a word's count is known beforehand
                    once = np.flatnonzero(n == 1)
                    best[once] = [of_group[crc32(w[-3:]) % groups] for w in word.take(pa.array(once)).cast(pa.binary()).to_pylist()]
                yield pa.RecordBatch.from_arrays([word, pa.array(n), pa.array(best.astype(np.int32))], names=["word", "n", "class"])

        return run

    chosen = by_key(near_table, "word", choose(False), "word long, n long, class int").filter("n > 1").select("word", "class").toArrow()  # at most table_words
    of_table[np.asarray(chosen.column("word"))] = np.asarray(chosen.column("class"))
    rare = table(by_key(near_rest, "word", choose(True), "word string, n long, class int"), "lm-rare")

    mass = np.bincount(of_table, n_known + 0.5, classes).astype(np.float64)
    mass[0] += n_end + 0.5
    for c, m in rare.groupBy("class").agg(F.sum(F.col("n") + 0.5)).collect():
        mass[c] += m
    share = np.maximum(mass / norm, 1e-12)
    final = spark.sparkContext.broadcast((classes, of_table, of_group))
    links = table(rare_links(encoded, rare, final, norm), "lm-links")
    moves = counted(pair_counts(train, spark.sparkContext.broadcast((classes, of_table, np.full(groups, -1)))), classes).astype(np.float64)
    for key, n in links.filter("train").select(F.explode("keys").alias("key")).groupBy("key").count().collect():
        moves[key // classes, key % classes] += n
    return Fitted(units, n_known, n_end, int(total), norm, of_table, of_group, rare, gains(moves, share, pull, blend), encoded, links)


def score(docs: DataFrame, **how) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score for every row of docs; how: as for fit.

    Null texts count as empty (one token, the end).  A null doc_id counts as the empty string and is trained
    on.  Rows that share a doc_id are scored each, and every row counts in training.  Without training texts all counts are zero.
    ``pull`` smooths transitions towards the unigram share of a class, ``blend`` mixes in the unigram model."""
    fitted = fit(docs, **how)
    norm, n_end, groups, encoded, links = fitted.norm, fitted.n_end, fitted.units.groups, fitted.encoded, fitted.links
    model = docs.sparkSession.sparkContext.broadcast((fitted.of_table, fitted.gain, np.log10((fitted.n_known + 0.5) / norm), float(np.log10((n_end + 0.5) / norm))))

    def read():
        of_table, gain, logs, end = model.value
        flat_gain, classes = gain.ravel(), len(gain)

        def step(batch):
            flat, ends = chain(batch)
            here = looked_up(flat, of_table, np.full(groups, -1), 0)
            held = (here[:-1] >= 0) & (here[1:] >= 0)
            more = np.where(held, flat_gain[np.where(held, here[:-1] * classes + here[1:], 0)], 0.0)
            known = flat >= 0
            base = np.zeros(len(flat))
            base[known] = logs[flat[known]]
            begin = np.r_[0, ends[:-1]]
            per = lambda x: np.add.reduceat(x, begin)
            n_tokens = ends - begin
            out = {"row": column(batch, "row"), "doc_id": column(batch, "doc_id"), "n_tokens": pa.array(n_tokens)}
            return out | {"n_known": pa.array(per(known[:-1].astype(np.int64)) + (n_end > 0)), "base": pa.array(per(base[:-1]) + end), "more": pa.array(per(more))}

        return step

    def linked():
        flat_gain = model.value[1].ravel()

        def step(batch):
            keys = column(batch, "keys")
            of = np.repeat(np.arange(len(keys)), np.diff(np.asarray(keys.offsets)))
            more = np.bincount(of, flat_gain[np.asarray(keys.flatten())], len(keys))
            return {"row": column(batch, "row"), "rest": column(batch, "rest"), "rest_known": column(batch, "rest_known"), "rest_more": pa.array(more)}

        return step

    kept = arrow_map(encoded.select("row", "doc_id", "ids"), read, "row long, doc_id long, n_tokens long, n_known long, base double, more double")
    out = kept.join(arrow_map(links.drop("train"), linked, "row long, rest double, rest_known long, rest_more double"), "row", "left").na.fill(0, ["rest", "rest_known", "rest_more"])
    base_score = F.col("base") + F.col("rest")
    return out.select(
        "doc_id", held_out(F.col("doc_id")).alias("held_out"), "n_tokens", (F.col("n_known") + F.col("rest_known")).alias("n_known"), F.lit(fitted.total).cast("long").alias("train_tokens"),
        base_score.alias("base_score"), (base_score + F.col("more") + F.col("rest_more")).alias("score"),
    )
