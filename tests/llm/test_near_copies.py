"""Near copies of the pipeline's stage against all pairs."""

import random
from collections import Counter

import numpy as np
import pytest

import corpus_pipeline
from walkrank.llm import near_copies, simhash


def shingles(text):
    w = text.lower().split()
    return {" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def edited(rng, words, times):
    words = list(words)
    for _ in range(times):
        words[rng.randrange(len(words))] = f"new{rng.random()}"
    return words


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(4)
    passage = [f"p{i}" for i in range(30)]
    out = []
    for i in range(40):
        base = [f"w{rng.randrange(400)}" for _ in range(rng.choice([3, 6, 60, 150, 400]))]
        base += passage * (i % 3 == 0)
        out += [base, *(edited(rng, base, rng.randrange(1, 2 + len(base) // 40)) for _ in range(rng.randrange(4)))]
    crowd = [f"c{i}" for i in range(120)]
    out += [edited(rng, crowd, k % 4) for k in range(80)] + [[], []]
    rng.shuffle(out)
    return [(i, " ".join(w)) for i, w in enumerate(out)]


def kept(rows):
    sets = [shingles(t) for _, t in rows]
    up = list(range(len(rows)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    missed = 0
    for i in range(len(rows)):
        for j in range(i):
            if sets[i] == sets[j] or 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]):
                missed += (simhash.fingerprint(rows[i][1]) ^ simhash.fingerprint(rows[j][1])).bit_count() > 3
                a, b = sorted((root(i), root(j)))
                up[b] = a
    assert missed > 100  # 3 bits don't reach them
    return [rows[i][0] for i in range(len(rows)) if root(i) == i]


@pytest.mark.parametrize("frequent", [4, 10**6])
def test_stage_finds_all(spark, rows, monkeypatch, frequent):
    monkeypatch.setattr(near_copies, "FREQUENT", frequent)
    docs = spark.createDataFrame([(k, t, None, None, len(t)) for k, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(r.doc_id for r in corpus_pipeline.without_near_copies(spark, docs, "").collect()) == kept(rows)


def test_shared_pairs_across_batches(spark, rows):
    """The search without SimHash's links, on Arrow batches that cut shingles in two."""
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("doc_id", "text", "xxhash64(text) as key")
    sets = near_copies.common.written(near_copies.sets_of(docs).dropDuplicates(["id"]), "test-sets")
    none = sets.selectExpr("id as node", "id as root").limit(0)
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 7)
    try:
        got = {(r.a, r.b) for r in near_copies.shared_pairs(sets, none).collect()}
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)
    text, of = dict(rows), {r.id: r.doc_id for r in sets.collect()}
    whole = {k: shingles(text[d]) for k, d in of.items()}
    names = sorted(whole)
    want = {(a, b) for i, a in enumerate(names) for b in names[i + 1 :] if whole[a] and 5 * len(whole[a] & whole[b]) >= 4 * len(whole[a] | whole[b])}
    assert len(want) > 100 and want <= got


@pytest.mark.parametrize("counted", [0, 10**9])
def test_counting_a_share_changes_no_row(spark, rows, monkeypatch, counted):
    """Frequent shingles counted on an eighth of the texts and on all: other orders, the same groups."""
    monkeypatch.setattr(near_copies, "COUNTED", counted)
    monkeypatch.setattr(near_copies, "FREQUENT", 4)
    docs = spark.createDataFrame([(k, t, None, None, len(t)) for k, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(r.doc_id for r in corpus_pipeline.without_near_copies(spark, docs, "").collect()) == kept(rows)


@pytest.mark.parametrize("counted", [0, 10**9])
def test_all_shingles_are_counted(spark, rows, monkeypatch, counted):
    """Each shingle of each text, however many texts there are and however they lie."""
    monkeypatch.setattr(near_copies, "COUNTED", counted)
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("doc_id", "text", "xxhash64(text) as key").repartition(5)
    want = Counter(int(h) for _, t in rows for h in near_copies.shingle_set(t))
    got = near_copies.frequent_shingles(docs)
    assert int(got.sum()) == sum(want.values())
    assert (got[near_copies.counter_of(np.array(list(want), np.uint64))] >= np.array(list(want.values()), np.uint64)).all()
    assert max(want.values()) >= 40  # the crowd's shingles are frequent
