"""The pipeline against a plain version of its stages on a small fixture."""

import hashlib

import public_tokenizers
import pytest
from tokenizers import Tokenizer

from nearcohort.llm import decontaminate, quality

SF = "/root/testdata/sf0.001"
corpus_pipeline = pytest.importorskip("corpus_pipeline")


def components(docs):
    sets = {i: decontaminate.word_shingles(t, 5) for i, t in docs}
    up = {i: i for i in sets}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in sorted(sets):
        for b in sorted(sets):
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                up[max(x, y)] = min(x, y)
    return {i: find(i) for i in sets}


def test_pipeline_equals_plain_stages(spark):
    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    frame = spark.read.parquet(f"{SF}/documents.parquet")
    model = quality.fit(frame, spark.read.parquet(f"{SF}/labels.parquet"))
    good = {r["doc_id"] for r in quality.score(frame, model).where("predicted = 1").collect()}
    docs = {i: t for i, t in docs.items() if i in good}
    last = {}
    for i in sorted(docs):
        last[docs[i]] = i
    docs = {i: t for t, i in last.items()}
    comp = components(list(docs.items()))
    docs = {i: t for i, t in docs.items() if comp[i] == i}
    items = [decontaminate.word_shingles(r["text"], 5) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    own = {i: decontaminate.word_shingles(t, 5) for i, t in docs.items()}
    docs = {i: t for i, t in docs.items() if not any(q and 100 * len(q & own[i]) >= 80 * len(q) for q in items)}
    lib = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    got = {r["doc_id"]: r for r in corpus_pipeline.run(spark, SF).collect()}
    assert set(got) == set(docs) and len(docs) > 100
    for i, t in docs.items():
        assert got[i]["n_tokens"] == len(lib.encode(t, add_special_tokens=False).ids)
        assert got[i]["decoded_sha256"] == hashlib.sha256(t.encode()).hexdigest()


def test_stages_keep_the_columns(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    assert len(corpus_pipeline.STAGES) == 5
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, SF).columns == docs.columns
