"""Operators against brute force, and on awkward and empty tables."""

import hashlib
import random
from collections import Counter, defaultdict
from math import log10
from zlib import crc32

import numpy as np
import pytest
from pyspark.sql import functions as F
from vsketch.llm import classlm, decontam, fst_bpe, minhash, ordinal, pii, quality, sharding, spotsigs, substring

from .conftest import AWKWARD, words

sha = lambda b: hashlib.sha256(b).hexdigest()
LABELS = "doc_id long, quality int, toxic int"


def unique(pairs):
    """Rows with own ids: the order of unique_ids."""
    return sorted(set(pairs), key=lambda p: (p[0] is not None, p[0] or 0, p[1] is not None, p[1] or ""))


def test_sharding(spark, make):
    rng = random.Random(4)
    pairs = [(i, "t" * rng.randint(0, 400) if i % 5 else "copy" * 40) for i in range(300)]
    got = sharding.shard(make(pairs), 7, rows_a_block=10).collect()
    assert len(got) == 300
    sizes, slots, home = Counter(), defaultdict(list), {}
    for r in got:
        t = pairs[r["doc_id"]][1]
        assert r["size"] == len(t.encode()) + 1 and r["text_crc32"] == crc32(t.encode()) and r["law"] == "bytes" and r["grown_shard"] is None
        sizes[r["shard"]] += r["size"]
        slots[r["shard"]].append(r["slot"])
        assert home.setdefault(t, r["shard"]) == r["shard"]
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    first, size = {}, Counter()
    for i, t in pairs:
        first.setdefault(t, i)
        size[t] += len(t) + 1
    order = [size[t] for t in sorted(first, key=first.get)]

    def fits(cap):
        n, now = 1, 0
        for s in order:
            if s > cap:
                return False
            n, now = (n, now + s) if now + s <= cap else (n + 1, s)
        return n <= 7

    best = min(c for c in range(max(order), sum(order) + 1) if fits(c))
    assert max(sizes.values()) == best
    out = sharding.shard(make(AWKWARD), 16).collect()
    assert len(out) == len(AWKWARD) and all(0 <= r["shard"] < 16 for r in out)
    assert sharding.shard(make([]), 16).count() == 0


def test_refined_cells_are_exact():
    rng = random.Random(1)
    sizes = [rng.randint(1, 90) for _ in range(200)]
    fine = sharding.Cells([(i, i, s) for i, s in enumerate(sizes)])
    coarse = sharding.Cells([(i, i + 9, sum(sizes[i : i + 10])) for i in range(0, 200, 10)])
    while todo := coarse.unsure(6):
        gone = set(todo)
        fresh = [(i, i, sizes[i]) for j in todo for i in range(coarse.rows[j][0], coarse.rows[j][1] + 1)]
        coarse = sharding.Cells([r for i, r in enumerate(coarse.rows) if i not in gone] + fresh)
    assert coarse.capacity(6, False) == fine.capacity(6, False) and coarse.cuts(fine.capacity(6, False), 6) == fine.cuts(fine.capacity(6, False), 6)


def test_decontamination(spark, make):
    items = spark.createDataFrame([(11, words(14, 5)), (2, "w900 w901"), (3, None), (4, "?!"), (5, "zz")], "item_id long, text string")
    pairs = [*AWKWARD, (20, "A W900, w901! b"), (21, words(9, 5))]
    bench = {"11": words(14, 5).split(), "2": ["w900", "w901"], "5": ["zz"]}
    whole = decontam.report(make(pairs), items)
    blocks = decontam.scan(make(pairs), items, limit=40)  # a benchmark beyond the broadcast bound
    got, again = (Counter(map(tuple, f.collect())) for f in (whole, whole))
    want = Counter()
    for i, t in pairs:
        w = decontam.words_of((t or "").encode())
        w = [x.decode() for x in w]
        hit, found = set(), []
        for name, own in bench.items():
            n = min(10, len(own))
            grams = {tuple(own[k : k + n]) for k in range(len(own) - n + 1)}
            at = [k for k in range(len(w) - n + 1) if tuple(w[k : k + n]) in grams]
            hit.update(p for k in at for p in range(k, k + n))
            found += [name] * bool(at)
        want[(i, len(w), len(hit), len(found), sha(",".join(sorted(found)).encode()), bool(hit))] += 1
    assert got == want == again
    n_hit = {(r["doc_id"], sum(s["b"] - s["a"] for s in r["spans"])) for r in blocks.collect()}
    assert n_hit == {(k[0], k[2]) for k in want} and blocks.count() == len(pairs)
    assert decontam.report(make([]), items).count() == 0 and decontam.report(make(pairs), items.limit(0)).filter("contaminated").count() == 0
    kept = decontam.remove_documents(make(pairs), items)
    assert kept.columns == make([]).columns and kept.count() == sum(n for k, n in want.items() if not k[5])
    cut = {r[0]: r[1] for r in decontam.remove_spans(make([(20, "A W900, w901! b")]), items).collect()}
    assert cut == {20: "A ! b"}


def test_decontamination_in_blocks_judges_the_input(spark, make):
    """Repeated and null ids, and items that overlap in the text: any number of blocks gives the same."""
    items = spark.createDataFrame([(1, "p q"), (1, "a b"), (1, "p q"), (2, "a p"), (None, "n n"), (3, "p q"), (4, None)], "item_id long, text string")
    docs = make([(20, "x a p q b y"), (21, "n n"), (22, "A, b!"), (22, "A, b!"), (23, None), (None, "p q"), (24, "")])
    one, many = 1 << 20, 3
    rows = lambda f: Counter(map(str, f.collect()))
    for how in (decontam.report, decontam.remove_documents, decontam.remove_spans):
        assert rows(how(docs, items, 2, one)) == rows(how(docs, items, 2, many)), how
    got = {r["doc_id"]: (r["n_hit"], r["n_items"], r["items_sha256"]) for r in decontam.report(docs, items, 2).collect()}
    assert got[20] == (3, 3, sha(b"1,2,3")) and got[21] == (2, 0, sha(b"")) and got[22] == (2, 1, sha(b"1"))
    assert {r[0]: r[1] for r in decontam.remove_spans(docs, items, 2, many).collect()} == {20: "x  b y", 21: "", 22: "!", 23: None, None: "", 24: ""}
    assert sorted(r[0] for r in decontam.remove_documents(docs, items, 2, many).collect()) == [23, 24]


def test_language_model(spark, make):
    rng = random.Random(7)
    pairs = [(i, " ".join(rng.choice("abcdefgh") + rng.choice(("x", "", "yy")) for _ in range(rng.randint(0, 40)))) for i in range(120)] + [(200, None), (None, "a b"), (3, "A a")]
    frame = classlm.score(make(pairs), classes=6, words=8, groups=4, table_words=10)
    got = sorted(map(tuple, frame.select(F.coalesce("doc_id", F.lit(-1)), "n_tokens", "n_known", F.round("base_score", 8), "held_out", "train_tokens").collect()))
    out = lambda i: crc32(("" if i is None else str(i)).encode()) % 5 == 1
    c = Counter()
    for i, t in pairs:
        if not out(i):
            c.update((t or "").lower().split() + [None])
    n, v = sum(c.values()), len(c)
    want = []
    for i, t in pairs:
        toks = (t or "").lower().split() + [None]
        want.append((-1 if i is None else i, len(toks), sum(c[x] > 0 for x in toks), round(sum(log10((c[x] + 0.5) / (n + 0.5 * (v + 1))) for x in toks), 8), out(i), n))
    assert [x[:3] + x[4:] for x in got] == [x[:3] + x[4:] for x in sorted(want)]
    assert all(abs(a[3] - b[3]) < 1e-6 for a, b in zip(got, sorted(want), strict=True))
    assert classlm.score(make([]), classes=4, words=4, groups=2).count() == 0


def test_class_model_scores_by_brute_force(make):
    """The score of every text from word classes and counted transitions; probabilities sum to 1."""
    rng = random.Random(21)
    vocabulary = [f"w{i}" for i in range(40)]
    pairs = [(i, " ".join(rng.choice(vocabulary[: 5 + i % 36]) for _ in range(rng.randint(0, 25)))) for i in range(150)] + [(500, "unseen w1 unseen2"), (501, None)]
    how = dict(classes=5, words=6, groups=3, table_words=12, pull=2.0, blend=0.1)
    model = classlm.fit(make(pairs), **how)
    got = {r["doc_id"]: r["score"] for r in classlm.score(make(pairs), **how).collect()}
    train = lambda i: crc32(str(i).encode()) % 5 != 1
    texts = {i: (t or "").split() for i, t in pairs}
    c = Counter(w for i, t in texts.items() if train(i) for w in [*t, None])
    norm = sum(c.values()) + 0.5 * (len(c) + 1)
    home = {w.decode(): int(model.of_table[k]) for w, k in model.units.place.items()} | {r["word"]: r["class"] for r in model.rare.collect()} | {None: 0}
    assert set(home) == set(c)
    class_of = lambda w: home[w] if w in home else int(model.of_group[crc32(w.encode()[-3:]) % 3])
    moves, share = np.zeros((5, 5)), np.zeros(5)
    for i, t in texts.items():
        if train(i):
            line = [0, *map(class_of, t), 0]
            for a, b in zip(line, line[1:], strict=False):
                moves[a, b] += 1
    for w, n in c.items():
        share[home[w]] += (n + 0.5) / norm
    step = (moves + 2.0 * share) / (moves.sum(1, keepdims=True) + 2.0)
    chance = lambda w, before: 0.9 * step[before, class_of(w)] * (c[w] + 0.5) / norm / share[class_of(w)] + 0.1 * (c[w] + 0.5) / norm
    for i, t in texts.items():
        line = [None, *t, None]
        want = sum(log10(chance(b, class_of(a))) for a, b in zip(line, line[1:], strict=False))
        assert abs(got[i] - want) < 1e-6, (i, got[i], want)
    for before in range(5):  # what unseen words share is half a count
        assert 1 - 0.5 / norm - 1e-9 <= sum(chance(w, before) for w in c) <= 1 + 1e-9


def test_exchange_finds_alternating_classes():
    pairs = np.zeros((9, 9))
    for a in range(1, 9):
        for b in range(1, 9):
            pairs[a, b] = 50 if (a % 2) != (b % 2) else 1
    pairs[0, 1:] = pairs[1:, 0] = 3
    home = classlm.exchange(pairs, 3)
    assert len({home[i] for i in (1, 3, 5, 7)}) == 1 and len({home[i] for i in (2, 4, 6, 8)}) == 1 and home[1] != home[2]


def test_words_beyond_the_head_get_the_class_of_their_contexts(make):
    # red and sky words alternate; in every spelling group (last three bytes) both kinds stand, so spelling says nothing
    rng = random.Random(3)
    a, b = ([f"{k}{i}end" for i in range(30)] for k in "rs")
    texts = [" ".join(rng.choice(("R1", "R2", *a) if i % 2 else ("S1", "S2", *b)) for i in range(40)) for _ in range(200)]
    ask = [(10_000 + i, t) for i, t in enumerate(["r3end s4end r5end s6end", "r3end r4end r5end r6end"])]
    for table_words in (4, 1000):  # words beyond the head in the table, and joined by word
        got = {r["doc_id"]: r["score"] - r["base_score"] for r in classlm.score(make([*enumerate(texts), *ask]), classes=4, words=4, groups=2, table_words=table_words).collect()}
        assert got[10_000] > got[10_001] + 1


def test_language_model_in_small_batches_and_without_lists(spark, make):
    """Words and texts that span batches give the same scores, and nothing is collected into lists."""
    rng = random.Random(13)
    docs = make([(i, " ".join(rng.choice("abcdefgh") + rng.choice(("x", "", "yy", "zzz")) for _ in range(rng.randint(0, 40)))) for i in range(90)])
    how = dict(classes=5, words=6, groups=3, table_words=9)
    score = lambda: sorted((r["doc_id"], r["n_known"], round(r["base_score"], 8), round(r["score"], 8)) for r in classlm.score(docs, **how).collect())
    want, key = score(), "spark.sql.execution.arrow.maxRecordsPerBatch"
    before, lists = spark.conf.get(key), F.collect_list
    try:
        spark.conf.set(key, "2")
        F.collect_list = None
        assert score() == want
    finally:
        spark.conf.set(key, before)
        F.collect_list = lists


def test_exchange_ends_where_no_unit_moves():
    rng = np.random.default_rng(5)
    pairs = rng.poisson(rng.gamma(0.3, 4, (60, 60))).astype(float)
    home = classlm.exchange(pairs, 6)

    def likelihood(h):
        hot = (h[:, None] == np.arange(6)).astype(float)
        both = hot.T @ pairs @ hot
        return classlm._f(both).sum() - classlm._f(both.sum(0)).sum() - classlm._f(both.sum(1)).sum()

    best = likelihood(home)
    for u in range(1, 60):
        for c in range(1, 6):
            assert likelihood(np.where(np.arange(60) == u, c, home)) <= best + 1e-6


def near_truth(texts, size, percent, fold=True):
    sets = []
    for t in texts:
        w = (t or "").encode()
        w = (w.lower() if fold else w).split()
        n = min(size, len(w))
        sets.append({tuple(w[k : k + n]) for k in range(len(w) - n + 1)} if w else set())
    root = list(range(len(texts)))

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if both and 100 * both >= percent * (len(sets[i]) + len(sets[j]) - both):
                root[max(top(i), top(j))] = min(top(i), top(j))
    return [len(s) for s in sets], [top(i) for i in range(len(texts))]


def edited(rng, base, n):
    w = list(base)
    for _ in range(n):
        w[rng.randrange(len(w))] = f"e{rng.randrange(10**6)}"
    return " ".join(w)


def test_near_duplicates_with_a_hot_group(spark, make):
    rng = random.Random(5)
    base = [f"b{rng.randrange(10**6)}" for _ in range(150)]
    pairs = [(1000 - i, edited(rng, base, rng.randint(0, 14))) for i in range(150)] + [(2000 + i, words(rng.randint(1, 6), i % 4)) for i in range(40)] + [(3000, None), (3001, "")]
    pairs.sort()
    for size, percent in ((3, 85), (5, 80)):
        got = minhash.near_duplicates(make(pairs), size, percent).orderBy("doc_id").collect()
        n, top = near_truth([t for _, t in pairs], size, percent)
        assert [r["n_shingles"] for r in got] == n
        assert [r["component_id"] for r in got] == [pairs[k][0] for k in top]
        assert [r["kept"] for r in got] == [i == k for i, k in enumerate(top)]


def test_near_duplicates_awkward(spark, make):
    own = unique(AWKWARD)
    n, top = near_truth([t for _, t in own], 3, 85)
    want = Counter()
    for (i, t), size, k in zip(own, n, top, strict=True):
        want[(i, size, own[k][0])] += AWKWARD.count((i, t))
    assert Counter(tuple(r)[:3] for r in minhash.near_duplicates(make(AWKWARD)).collect()) == want
    assert minhash.near_duplicates(make([])).count() == 0
    kept = minhash.keep_first(make(AWKWARD), 3, 85)
    assert kept.columns == make([]).columns and kept.count() == sum(i == k for i, k in enumerate(top))


@pytest.mark.parametrize("few", [0, 10, 500_000])
def test_components_in_one_task_and_in_many(spark, monkeypatch, few):
    monkeypatch.setattr(minhash, "ONE_TASK", few)
    rng = random.Random(few)
    chain = [(k, k + 1) for k in range(100, 115)]
    links = [(rng.randrange(60), rng.randrange(60)) for _ in range(40)] + chain
    first = minhash.components(spark.createDataFrame(links[:30], "a long, b long"))
    got = {r[0]: r[1] for r in minhash.components(spark.createDataFrame(links[30:], "a long, b long"), first).collect()}
    root = {x: x for p in links for x in p}
    for _ in root:
        for a, b in links:
            root[a] = root[b] = min(root[a], root[b])
    assert got == root


def test_bayesian_bounds():
    need = minhash.least_matches(85)
    assert need == sorted(need) and 0 < need[0] < 0.85 * minhash.BATCH
    assert minhash.band_rows(85) == 5 and minhash.band_rows(80) == 4


def test_fingerprints(spark, make):
    pairs = [(i, f"the house {words(3, i)} and a {words(4, 3 * i)} of é tree{i} to {words(2)}"[: 30 + 7 * i]) for i in range(30)] + [(40, None), (41, "?!?"), (42, "?!?"), (43, "")]
    got = {r["doc_id"]: r for r in spotsigs.neighbours(make(pairs), part_bytes=300).collect()}
    assert len(got) == len(pairs)
    for k, (i, t) in enumerate(pairs):
        t, after = t or "", pairs[(k + 1) % len(pairs)][1] or ""
        n = len(t) // 4
        e = t[: len(t) - n] + after[:n]
        a, b, c = (spotsigs.signatures(x) for x in (t, e, after))
        r = got[i]
        assert (r["n_chars"], r["edited_sha256"], r["fingerprint"], r["edited_fingerprint"]) == (len(t), sha(e.encode()), spotsigs.fingerprint(a), spotsigs.fingerprint(b))
        assert r["near_edited"] == spotsigs.likeness(a, b) and r["near_next"] == spotsigs.likeness(a, c)
        assert (spotsigs.parse(r["fingerprint"]) == a).all()
    assert got[40]["fingerprint"] == "" and got[41]["near_next"] == 1.0
    assert spotsigs.neighbours(make(AWKWARD)).count() == len(AWKWARD) and spotsigs.neighbours(make([])).count() == 0
    assert spotsigs.neighbours(make([(1, "alone in the big house here")])).first()["near_next"] == 1.0
    same = {r[0]: r[1] for r in spotsigs.near_classes(make([(1, pairs[9][1]), (2, pairs[9][1]), (3, "?"), (4, None)])).collect()}
    assert same == {1: 1, 2: 1, 3: 3, 4: 4}


def test_near_classes_equal_all_pairs(spark, make):
    """Length partitions and pruning lose no link: hot groups of near copies, chains of lengths, hot signatures."""
    rng = random.Random(5)
    anchors = ("the", "a", "of", "to", "in")
    said = lambda k, n: " ".join(f"{rng.choice(anchors)} c{rng.randrange(k)} d{rng.randrange(k)}" for _ in range(n))
    pairs = []
    for i in range(12):  # families whose lengths differ by a few signatures
        own = [f"the f{i} g{j}" for j in range(rng.randint(8, 60))]
        for _ in range(9):
            cut = own[: len(own) - rng.randint(0, max(1, len(own) // 4))]
            pairs.append(" ".join(cut + [said(40, rng.randint(0, 3))]))
    hot = said(30, 60)
    pairs += [hot + f" the x{i} y{i}" for i in range(150)] + [hot] * 40
    pairs += [said(2, rng.randint(3, 9)) for _ in range(80)]  # few signatures, often repeated
    rng.shuffle(pairs)
    docs = [(i * 3, t) for i, t in enumerate(pairs)] + [(9000, None), (9001, ""), (9002, "!"), (9003, "!")]
    prints = [spotsigs.signatures(t or "") for _, t in docs]
    for percent in (80, 50, 100):
        label = list(range(len(docs)))
        top = lambda x: x if label[x] == x else top(label[x])  # noqa: B023,E731
        for i in range(len(docs)):
            for j in range(i):
                if (len(prints[i]) and len(prints[j]) or docs[i][1] == docs[j][1]) and 100 * spotsigs.likeness(prints[i], prints[j]) >= percent - 1e-9:
                    label[max(top(i), top(j))] = min(top(i), top(j))
        # texts without signatures are one class only where they are equal fingerprints
        got = dict(map(tuple, spotsigs.near_classes(make(docs), percent).collect()))
        want = {d: docs[top(i)][0] for i, (d, _) in enumerate(docs)}
        want[9001] = want[9000] = 9000
        assert got == want, percent


def test_substring_removal(spark, make):
    own = unique(AWKWARD)
    seen, want = set(), Counter()
    for i, t in own:
        w = (t or "").encode().split()
        gone = set()
        for k in range(len(w) - 19):
            g = tuple(w[k : k + 20])
            if g in seen:
                gone.update(range(k, k + 20))
            seen.add(g)
        kept = b" ".join(x for k, x in enumerate(w) if k not in gone)
        want[(i, len(w), len(gone), sha(kept))] += AWKWARD.count((i, t))
    assert Counter(map(tuple, substring.removal(make(AWKWARD)).collect())) == want
    assert substring.removal(make([])).count() == 0


def test_substring_blocks_without_repeats(spark, make):
    """A block may hold no repeated minimizer, or open windows of which none repeats inside it."""
    pairs = [(i, words(80, 100 * i)) for i in range(6)]
    assert {r["n_removed"] for r in substring.removal(make(pairs).coalesce(1)).collect()} == {0}
    apart = make(pairs).unionByName(make([(10, "x " + words(80)), (11, "y")]))
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substring.removal(apart).collect()}
    assert len(got) == 8 and got[10] == (81, 80, sha(b"x")) and got[0] == (80, 0, sha(words(80).encode()))


def test_substring_windows_are_dealt_evenly(spark, make, monkeypatch):
    """No part holds much more than others: in ranges of minimizers the lowest of 16 would have half of the windows."""
    rng, seen, spans = random.Random(8), [], substring._spans
    pairs = [(2 * i, "copy0 " + " ".join(f"w{rng.randrange(50_000)}" for _ in range(200))) for i in range(100)]
    pairs += [(i + 1, t.replace("copy0", "copy1")) for i, t in pairs]
    monkeypatch.setattr(substring, "_ranges", lambda docs, gram: 4)
    monkeypatch.setattr(substring, "_spans", lambda judged, window: seen.append(judged) or spans(judged, window))
    assert sum(r["n_removed"] for r in substring.removal(make(pairs)).collect()) == 100 * 200
    sizes = [r[0] for r in seen[0].filter(F.col("kind") == substring.WINDOWS).groupBy("part").agg((F.sum(F.octet_length("hash")) / 8).alias("n")).select("n").collect()]
    assert sum(sizes) >= 100 * 181 and max(sizes) < 0.2 * sum(sizes)


@pytest.mark.parametrize("alphabet", ["ab", "abc "])
def test_substring_removal_of_runs(spark, make, alphabet):
    rng = random.Random(2)
    pairs = [(i, " ".join(rng.choice(alphabet).strip() or "q" for _ in range(rng.randint(0, 60)))) for i in range(25)] + [(99, "r " * 80)]
    seen, want = set(), set()
    for i, t in pairs:
        w, gone = t.split(), set()
        for k in range(len(w) - 4):
            g = tuple(w[k : k + 5])
            if g in seen:
                gone.update(range(k, k + 5))
            seen.add(g)
        want.add((i, len(w), len(gone), sha(" ".join(x for k, x in enumerate(w) if k not in gone).encode())))
    assert set(map(tuple, substring.removal(make(pairs), window=5, gram=3).collect())) == want


@pytest.fixture(scope="module")
def bpe():
    P = pytest.importorskip("public_tokenizers")
    tiktoken = pytest.importorskip("tiktoken")
    path = P.path("byte_bpe_50k.tiktoken")
    ranks = fst_bpe.load_ranks(open(path, "rb").read())
    return path, P.PATTERN, tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={}), fst_bpe.Codec(ranks, P.PATTERN)


def test_bpe_equals_the_library(bpe):
    _, _, library, codec = bpe
    rng = random.Random(8)
    for alphabet in ("abcdefghijklmnopqrstuvwxyz", "aab", "ab \n\t\x0b\x1c\x85  ​", "éèüñ漢字кириллица 123٣²Ⅷ", "\U0001f600\U0001f1e6a!?..--''ss 'll"):
        for size in (1, 7, 60, 900):
            for _ in range(12):
                t = "".join(rng.choice(alphabet) for _ in range(size))
                ids = codec.encode(t)
                assert ids == library.encode_ordinary(t)
                assert "".join(x for _, x in codec.decode(ids, 5)) == t
    small = fst_bpe.Transducer(codec.fst.ranks, most_states=50, flush_every=16)  # states are dropped and made anew
    assert [small.encode(b"a" * n) for n in (5, 40, 1000)] == [tuple(library.encode_ordinary("a" * n)) for n in (5, 40, 1000)]


def test_bpe_with_small_memories_gives_the_same_ids(bpe):
    """States beyond the bound pass, the automaton starts afresh, and pieces change generations."""
    _, pattern, library, codec = bpe
    rng = random.Random(9)
    text = " ".join("".join(rng.choice("abcdeé漢") for _ in range(rng.randint(1, 9))) for _ in range(3000))
    small = fst_bpe.Codec(codec.fst.ranks, pattern, memory=64, most_states=40)
    small.fst.renew = 3
    assert small.encode(text * 2) == library.encode_ordinary(text * 2)
    assert len(small.known) <= 64 and len(small.fst.states) <= 40
    ids = small.numbers(text)
    assert b"".join(small.checked(text, ids)) == text.encode()
    with pytest.raises(ValueError):
        list(small.checked(text + "x", ids))


def test_utf8_stream_holds_back_open_characters():
    data, out, s = "aé漢\U0001f600z".encode(), "", fst_bpe.Utf8Stream()
    for b in data:
        out += s.feed(bytes([b]))
    assert out + s.feed(b"", end=True) == data.decode()
    bad = fst_bpe.Utf8Stream()
    assert bad.feed(b"\xff\xe0\x20\xf0\x9f") + bad.feed(b"", end=True) == b"\xff\xe0\x20\xf0\x9f".decode("utf-8", "replace")


def test_bpe_on_documents(spark, make, bpe):
    path, pattern, library, _ = bpe
    want = Counter()
    for i, t in AWKWARD:
        ids = library.encode_ordinary(t or "")
        want[(i, len(ids), sha(" ".join(map(str, ids)).encode()), sha((t or "").encode()))] += 1
    assert Counter(map(tuple, fst_bpe.report(make(AWKWARD), path, pattern).collect())) == want
    enc = fst_bpe.encode(make(AWKWARD), path, pattern)
    assert Counter(tuple(r) for r in fst_bpe.decode(enc, path, pattern).collect()) == Counter((i, t or "") for i, t in AWKWARD)
    assert fst_bpe.report(make([]), path, pattern).count() == 0


def test_ordinal_model_of_four_grades():
    rng = random.Random(3)
    texts = []
    for g in range(4):
        for _ in range(150):
            texts.append((" ".join([f"n{rng.randrange(300)}" for _ in range(30)] + [f"mark{k}" for k in range(g) for _ in range(2)]).encode(), g))
    rows = [ordinal.features(t) for t, _ in texts]
    model = ordinal.fit(rows[::2], [g for _, g in texts][::2])
    assert list(model.thresholds) == sorted(model.thresholds) and model.grades == [0, 1, 2, 3]
    latent = np.array([model.latent(t) for t, _ in texts[1::2]])
    grade = np.array([g for _, g in texts[1::2]])
    assert np.abs(model.expected(latent) - grade).mean() < 0.35
    tails = model.tails(latent)
    assert (np.diff(tails, axis=1) <= 1e-12).all()


def labelled(spark, n=160):
    rng = random.Random(6)
    clean = lambda: " ".join(rng.choice(("river", "stone", "green", "house", "walks", "over", "under", "tree")) for _ in range(25)).capitalize() + "."
    pairs, labels = [], []
    for i in range(n):
        t, q, tox = clean(), 1, 0
        if i % 4 == 0:
            t, q = " ".join(w.upper() + "!!" for w in t.split()), 0
        elif i % 4 == 1:
            t, tox = t.replace("house", "scum", 1) + " scum", 1
        pairs.append((i, t))
        labels.append((i, q, tox))
    return pairs, spark.createDataFrame(labels, LABELS)


def test_quality_and_toxicity(spark, make):
    pairs, labels = labelled(spark)
    half = labels.filter("doc_id % 2 = 0 or doc_id % 8 < 4")
    good = {r["doc_id"]: r for r in quality.quality(make(pairs), half).collect()}
    assert len(good) == len(pairs) and all(good[i]["kept"] == (i % 4 != 0) for i, _ in pairs)
    bad = {r["doc_id"]: r["toxic"] for r in quality.toxicity(make(pairs), half).collect()}
    assert all(bad[i] == (i % 4 == 1) for i, _ in pairs)
    kept = quality.keep_good(make(pairs), half)
    assert kept.columns == make([]).columns and kept.count() == sum(i % 4 != 0 for i, _ in pairs)
    assert quality.quality(make(AWKWARD), half).count() == len(AWKWARD)
    none = labels.limit(0)
    assert quality.quality(make(AWKWARD), none).filter("kept").count() == len(AWKWARD) and quality.toxicity(make(AWKWARD), none).filter("toxic").count() == 0
    assert quality.quality(make([]), half).count() == 0 == quality.toxicity(make([]), half).count()


def test_grades_by_brute_force(spark, make):
    """Sample, screening, expected grade and tails against plain formulas, with hot, tied and null labels."""
    from math import exp, log

    rng = random.Random(12)
    pairs = [(i, " ".join([f"n{rng.randrange(40)}" for _ in range(20)] + ["low"] * (i % 3 == 0) + ["high"] * (i % 3 == 2) + ["x" * 300] * (i % 2))) for i in range(240)]
    labels = spark.createDataFrame([(i, i % 3, None) for i, _ in pairs] + [(i, i % 3, None) for i, _ in pairs[:50]] + [(None, 1, 1), (7, None, 0)], LABELS)
    rows = ordinal.sample(make(pairs), labels, "quality", 30).collect()
    assert Counter(r["grade"] for r in rows) == {0: 30, 1: 30, 2: 30} and len({r["doc_id"] for r in rows}) == 90
    model = ordinal.train(make(pairs), labels, "quality", 30)
    rows.sort(key=lambda r: r["doc_id"])
    found, grade = [ordinal.features(r["text"].encode()) for r in rows], [r["grade"] for r in rows]
    again = ordinal.fit(found, grade)
    assert np.allclose(model.weights, again.weights) and np.allclose(model.thresholds, again.thresholds) and model.grades == [0, 1, 2]

    def g2(f):  # presence against grade, from the four counts of each grade
        p, out = sum(f in x for x in found) / 90, 0.0
        for g in range(3):
            o = sum(f in x for x, y in zip(found, grade, strict=True) if y == g)
            out += sum(a * log(a / b) for a, b in ((o, 30 * p), (30 - o, 30 * (1 - p))) if a)
        return 2 * out

    assert set(np.flatnonzero(model.weights)) <= {f for f in set(np.concatenate(found).tolist()) if g2(f) >= 12}

    def penalised(weights, thresholds):
        out = -0.25 * float((weights**2).sum())
        for x, g in zip(found, grade, strict=True):
            over = [1.0, *(1 / (1 + exp(t - float(weights[x].sum()))) for t in thresholds), 0.0]
            out += log(over[g] - over[g + 1])
        return out

    best = penalised(model.weights.astype(float), model.thresholds)
    for f in np.flatnonzero(model.weights).tolist():
        for d in (-0.3, 0.3):
            moved = model.weights.astype(float)
            moved[f] += d
            assert penalised(moved, model.thresholds) < best + 0.02
    for d in (-0.3, 0.3):
        assert penalised(model.weights.astype(float), model.thresholds + d) < best + 0.02
    texts = {**dict(pairs), 900: None, 901: "", 902: "low low high"}
    got = {r[0]: r for r in ordinal.grade(make(list(texts.items())), model, at=1).collect()}
    for i, t in texts.items():
        score = sum(float(model.weights[f]) for f in set(ordinal.features((t or "").encode()).tolist()))
        over = [1 / (1 + exp(t_k - score)) for t_k in model.thresholds]
        assert abs(got[i]["expected"] - sum(over)) < 1e-5 and abs(got[i]["tail"] - over[1]) < 1e-5
    lone = ordinal.train(make(pairs), labels.filter("quality = 1"), "quality")
    assert lone.grades == [1] and ordinal.grade(make(pairs), lone).filter("expected <> 1 or tail <> 0").count() == 0


def test_long_words_and_shapes_count_whole():
    """No prefix decides: words of over 64 and shapes of over 256 bytes differ by their last byte."""
    a, b = b"x" * 5000 + b"1", b"x" * 5000 + b"2"
    assert set(ordinal.features(a)) != set(ordinal.features(b))
    a, b = b"aA0" * 200 + b"a", b"aA0" * 200 + b"Z"
    assert set(ordinal.features(a, with_words=False)) != set(ordinal.features(b, with_words=False))


def test_personal_data(spark, make):
    import re

    texts = ["mail a.b@c-d.org, x@y.z@w.q and a@b", "ip 1.2.3.4.5.6.7.8 and 300.1.1.1", "card 4111 1111 1111 1111 or 4111111111111112", "call +1 (656) 555-6669 or +12", 'token = "21135a35f4dd810370798c4b15d2cb12deb58dd9"', None, "", "é +49 30 1234567 ü"]
    pairs = [(i, t) for i, t in enumerate(texts * 40)] + [(i, t) for i, t in AWKWARD]

    def brute(t):
        out = [("email", *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
        out += [("ip", *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(x) <= 255 for x in m.group().split("."))]
        for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
            d = re.sub("[^0-9]", "", m.group())
            if 13 <= len(d) <= 19 and sum(sum(divmod(int(c) * (1 + k % 2), 10)) for k, c in enumerate(d[::-1])) % 10 == 0:
                out.append(("card", *m.span()))
        return out + [("phone", *m.span()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 9 <= len(re.sub("[^0-9]", "", m.group())) <= 15]

    rng = random.Random(3)
    for _ in range(3000):
        t = "".join(rng.choice(rng.choice(["a@b.c-.", "0123456789.", "0123456789 -", "+0123456789 ().-"])) for _ in range(rng.choice([5, 20, 60])))
        assert [(pii.KINDS[k], a, b) for k, a, b in pii.base_spans(t)] == brute(t)
    got = pii.report(make(pairs)).collect()
    assert Counter((r["doc_id"], r["n_email"], r["n_ip"], r["n_card"], r["n_phone"], r["base_sha256"]) for r in got) == Counter(
        (i, *(sum(s[0] == k for s in brute(t or "")) for k in ("email", "ip", "card", "phone")), sha(",".join(f"{k}:{a}:{b}" for k, a, b in brute(t or "")).encode())) for i, t in pairs
    )
    assert all(set(",".join(f"{k}:{a}:{b}" for k, a, b in brute(texts[0])).split(",")) <= set(r["spans"].split(",")) for r in got if r["doc_id"] == 0)
    assert any(r["spans"].startswith("secret:") for r in got)
    assert all(r["n_spans"] == len([x for x in r["spans"].split(",") if x]) >= r["n_email"] + r["n_ip"] + r["n_card"] + r["n_phone"] for r in got)
    key = texts[4].split('"')[1]
    secret = texts[4].index(key)
    found = {r["spans"] for r in got if (r["doc_id"] or 0) > 10 and r["doc_id"] % len(texts) == 4}  # ids up to 10 have other texts too
    assert found == {f"secret:{secret}:{secret + len(key)}"}
    clean = pii.redact(make(pairs)).collect()
    assert not any(brute(r["text"] or "") for r in clean) and all(r["n_chars"] == len(r["text"]) for r in clean if r["text"])
    assert pii.report(make([])).count() == 0 and pii.redact(make([])).count() == 0


def test_long_secrets_are_candidates():
    """No cap on the length of a key."""
    key = "a1b2c" * 1000  # no run of digits that could be a card
    text = f'token = "{key}" end'
    assert (pii.KINDS.index("secret"), 9, 5009) in pii.candidates(text, pii.base_spans(text))


def test_expectation_maximisation_separates_labelers():
    rng = np.random.default_rng(0)
    truth = rng.random(4000) < 0.4
    votes = np.stack([np.where(rng.random(4000) < p, truth, ~truth) for p in (0.95, 0.9, 0.85, 0.55, 0.8)], 1).astype(int)
    votes[rng.random(votes.shape) < 0.2] = 2
    prior, right, found = pii.expectation_maximisation(votes, np.ones(len(votes)))
    assert abs(prior - 0.4) < 0.05 and right[1][0] > right[1][3] and ((found > 0.5) == truth).mean() > 0.95
