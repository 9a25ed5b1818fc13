"""The pipeline, stage by stage, against plain Python on what each stage was given."""

import random
from math import exp

import pytest

import corpus_pipeline as P
from vsketch.llm import decontam, fst_bpe, ordinal, pii, quality

from .conftest import AWKWARD, rows
from .test_operators import LABELS, near_truth

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
FIVE = ["doc_id", "text", "lang", "source", "n_chars"]


def corpus():
    rng = random.Random(31)
    word = lambda: rng.choice(("river", "stone", "green", "house", "walks", "over", "under", "tree")) + rng.choice(("", "s", "ly", "ed"))
    said = lambda n: " ".join(word() for _ in range(n)).capitalize() + "."
    pairs, labels = [], []
    for i in range(120):
        t = said(rng.randint(20, 60))
        if i % 6 == 0:
            t = " ".join(w.upper() + "!!" for w in t.split())
        elif i % 6 == 1:
            t += f" Mail me: {word()}{i}@example.org or call +1 (656) 555-66{i % 10}9"
        pairs.append((i, t))
        labels.append((i, int(i % 6 != 0), 0))
    pairs += [(200 + i, pairs[2][1]) for i in range(5)]  # exact copies
    base = said(60).split()
    pairs += [(300 + i, " ".join(["X" + base[0], *base[1:], f"tail{i}"])) for i in range(5)]  # near copies
    passage = " ".join(f"item{k}" for k in range(14))
    pairs += [(400, said(20) + " " + passage), (401, said(20) + " " + passage.upper() + "!"), (402, said(20) + " " + " ".join(passage.split()[:9]))]
    return pairs, labels, [("b1", passage), ("b2", None), ("b3", "")]


@pytest.fixture(scope="module")
def sf(spark, tmp_path_factory):
    top = tmp_path_factory.mktemp("sf")
    pairs, labels, items = corpus()
    spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t)) for i, t in [*pairs, (500, None), (501, "")]], DOCS).write.parquet(f"{top}/documents.parquet")
    spark.createDataFrame(labels, LABELS).write.parquet(f"{top}/labels.parquet")
    spark.createDataFrame(items, "item_id string, text string").write.parquet(f"{top}/benchmark.parquet")
    return str(top)


def test_stages_and_their_order(spark, sf):
    pytest.importorskip("public_tokenizers")
    tiktoken = pytest.importorskip("tiktoken")
    import public_tokenizers

    assert [n for n, _ in P.STAGES] == ["quality classifier", "near-duplicates", "benchmark decontamination", "personal data", "encoding"] and P.ORACLE_SQL is None
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    given = {r["doc_id"]: r["text"] for r in docs.collect()}
    found = {}
    for k, (_, stage) in enumerate(P.STAGES):
        docs = spark.createDataFrame(stage(spark, docs, sf).collect(), docs.schema if k < 4 else None)
        assert docs.columns[:5] == FIVE and (k == 4 or docs.columns == FIVE)
        found[k] = {r["doc_id"]: r for r in docs.collect()}
        assert len(found[k]) == docs.count()

    model = ordinal.train(spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet"), "quality")
    tail = lambda t: 1 / (1 + exp(model.thresholds[0] - sum(float(model.weights[f]) for f in ordinal.features((t or "").encode()))))
    assert set(found[0]) == {i for i, t in given.items() if tail(t) >= quality.LEAST_TAIL}
    assert not any(i % 6 == 0 for i in found[0] if i < 120) and {i for i in range(120) if i % 6} <= set(found[0])

    ids = sorted(found[0])
    _, top = near_truth([found[0][i]["text"] for i in ids], 5, 80)
    assert set(found[1]) == {i for k, i in enumerate(ids) if top[k] == k}
    assert sum(i in found[1] for i in (2, *range(200, 205))) == 1 and sum(i in found[1] for i in range(300, 305)) == 1

    item = decontam.words_of(corpus()[2][0][1].encode())
    grams = {tuple(item[k : k + 10]) for k in range(len(item) - 9)}
    hit = lambda t: any(tuple(w[k : k + 10]) in grams for w in [decontam.words_of((t or "").encode())] for k in range(len(w) - 9))
    assert set(found[2]) == {i for i, r in found[1].items() if not hit(r["text"])} and {400, 401} & set(found[2]) == set() and 402 in found[2]

    assert set(found[3]) == set(found[2])
    for i, r in found[3].items():
        old = found[2][i]["text"]
        if old is None or not pii.base_spans(old):
            assert r["text"] == old or not i < 120
        else:
            assert not pii.base_spans(r["text"]) and "[EMAIL]" in r["text"] and r["n_chars"] == len(r["text"])
    assert any("[PHONE]" in (r["text"] or "") for r in found[3].values())

    ranks = fst_bpe.load_ranks(open(public_tokenizers.path("byte_bpe_50k.tiktoken"), "rb").read())
    library = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    assert {i: r["tokens"] for i, r in found[4].items()} == {i: library.encode_ordinary(r["text"] or "") for i, r in found[3].items()}

    whole = {r["doc_id"]: r["tokens"] for r in P.run(spark, sf).collect()}
    assert whole == {i: r["tokens"] for i, r in found[4].items()}


def test_stages_on_awkward_rows(spark, sf):
    """Nulls, repeats, empty and long texts, clashing columns and empty tables pass every stage."""
    pytest.importorskip("public_tokenizers")
    schema = "doc_id long, text string, lang string, source string, n_chars long, n_words string, shard string, tokens string, own_row_0 int, n_words_0 int, spans_0 int, items_0 int, row_0 int"
    for pairs in (AWKWARD, []):
        docs = spark.createDataFrame([(*r, 1, 2, 3, 4, 5) for r in rows(pairs)], schema)
        for k, (name, stage) in enumerate(P.STAGES):
            out = stage(spark, docs, sf)
            assert sorted(out.columns) == sorted(docs.columns), name
            got = out.collect()
            assert len(got) <= len(pairs) and all(r["own_row_0"] == 1 and r["n_words_0"] == 2 for r in got), name
            if k in (0, 2, 3, 4):
                assert len(got) == len(pairs) or k == 0, name
