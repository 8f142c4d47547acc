"""The pipeline against brute force, and its queries' SQL."""

import glob
import os
import random
from collections import Counter

import duckdb
import pytest

import corpus_pipeline
from tests.llm.test_near_copies import shingles
from tests.test_queries import canon
from walkrank.llm import common, decontamination, toxicity
from walkrank.llm.registry import ORACLES, QUERIES

SF = "/root/testdata/sf0.01"


def stages(spark, docs, sf_dir):
    out = []
    for k, (_, f) in enumerate(corpus_pipeline.STAGES):
        docs = common.written(f(spark, docs, sf_dir), f"test-{k}")
        out.append(docs)
    return out


def near_roots(texts):
    """For each text the first one reachable by similarities of 0.8 or more of five-word shingles."""
    sets = [shingles(t) for t in texts]
    up, held = list(range(len(texts))), {}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for i, s in enumerate(sets):
        shared = Counter(j for h in s for j in held.get(h, ()))
        if not s:
            shared = {j: 0 for j in range(i) if not sets[j]}
        for j, n in shared.items():
            if 5 * n >= 4 * (len(s) + len(sets[j]) - n):
                a, b = sorted((root(i), root(j)))
                up[b] = a
        for h in s:
            held.setdefault(h, []).append(i)
    return [root(i) for i in range(len(texts))]


def test_stages_by_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    after = stages(spark, docs, SF)
    rows = {r.doc_id: r.text for r in docs.collect()}
    lexicon = toxicity.learned(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    left = {k: t for k, t in rows.items() if lexicon.score(t or "") < 0.7}
    got = [{r.doc_id: r.text for r in x.collect()} for x in after]
    assert got[0] == left
    toxic = {r.doc_id for r in spark.read.parquet(f"{SF}/labels.parquet").where("toxic = 1").collect()}
    known = {r.doc_id for r in spark.read.parquet(f"{SF}/labels.parquet").where("toxic = 0").collect()}
    assert len(toxic & set(left)) <= 0.3 * len(toxic) and len(known - set(left)) <= 0.02 * len(known)
    norm = lambda s: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in s.strip(" \t\n\x0b\x0c\r"))
    held = {}
    for k, t in left.items():
        for line in {norm(x) for x in (t or "").split("\n")}:
            if len(line) >= 40:
                held.setdefault(line, []).append(k)
    lines = {k: "\n".join(x for x in (t or "").split("\n") if len(held.get(norm(x), ())) < 5 or max(held[norm(x)]) == k) for k, t in left.items()}
    assert got[1] == lines
    keys = sorted(lines)
    single = {keys[i]: lines[keys[i]] for i, r in enumerate(near_roots([lines[k] for k in keys])) if r == i}
    assert got[2] == single
    items = [(r.item_id, decontamination.words_of(r.text)) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    quoted = {k for k, t in single.items() for _, w in items if " ".join(w) in " ".join(decontamination.words_of(t))}
    assert quoted and not quoted & set(got[3]) and len(set(single) - set(got[3]) - quoted) <= 2
    assert got[4] == got[3]
    assert all(set(x.columns) == set(docs.columns) for x in after[:-1])
    assert all(r.n_chars == len(r.text) for r in after[1].collect())
    assert all(len(r.token_ids) == r.n_tokens for r in after[4].limit(20).collect())


def test_run_leaves_its_result_alone(spark):
    small = "/root/testdata/sf0.001"
    common.clear(spark)
    done = corpus_pipeline.run(spark, small)
    left = stages(spark, spark.read.parquet(f"{small}/documents.parquet"), small)[-1]
    assert sorted(r.doc_id for r in done.collect()) == sorted(r.doc_id for r in left.collect())
    common.clear(spark)
    corpus_pipeline.run(spark, small)
    folder = spark._jvm.org.apache.hadoop.fs.Path(common.work_dir(spark))
    assert [f.getPath().getName()[:7] for f in folder.getFileSystem(spark._jsc.hadoopConfiguration()).listStatus(folder)] == ["stage-5"]


def test_odd_documents(spark, tmp_path):
    schema = "doc_id long, text string, lang string, source string, n_chars long, doc string"
    rows = [(1, None), (2, ""), (None, None), (None, "words without an id"), (3, "a b c " * 30000), (4, "same text"), (4, "same text"), (5, "same text")]
    for name, kind in (("labels", "doc_id long, quality int, toxic int"), ("benchmark", "item_id long, text string")):
        spark.createDataFrame([], kind).write.parquet(f"{tmp_path}/{name}.parquet")
    for part in (rows, []):
        frame = spark.createDataFrame([(k, t, None, None, None, "x") for k, t in part], schema)
        last = stages(spark, frame, str(tmp_path))[-1]
        kept = [r.doc_id for r in last.collect()]
        assert sorted(x for x in kept if x) == ([1, 3, 4, 4] if part else []) and kept.count(None) == (2 if part else 0)


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for f in glob.glob("/root/testdata/sf0.001/*.parquet"):
        c.execute(f"create view {os.path.basename(f)[:-8]} as select * from '{f}'")
    return c


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_sql(spark, duck, name):
    assert canon(QUERIES[name](spark, "/root/testdata/sf0.001").toPandas()) == canon(duck.execute(ORACLES[name]).df())


def test_registered():
    import __spark_entry__

    names = set(__spark_entry__.queries())
    assert all(any(k.startswith(f"op{n}_") for k in names) for n in range(1, 11)) and "pipeline" in names
    random.seed(0)
