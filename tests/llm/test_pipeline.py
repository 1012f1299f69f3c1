import hashlib
import re

import corpus_pipeline
from purchase_planner.llm import bpe_lookup, curriculum, queries, subword_quality
from tests.conftest import SMALL
from tests.llm.test_operators import _brute_groups


def test_stages_against_brute_force(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    kept = corpus_pipeline.settle(corpus_pipeline.quality(spark, docs, SMALL))
    assert kept.columns == docs.columns
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{SMALL}/labels.parquet").collect()}
    ids = {r["doc_id"] for r in kept.select("doc_id").collect()}
    good = [d for d, q in labels.items() if q == 1]
    assert sum(d in ids for d in good) / len(good) > 0.97

    single = corpus_pipeline.settle(corpus_pipeline.near_duplicates(spark, kept, SMALL))
    rows = [(r["doc_id"], r["text"]) for r in kept.select("doc_id", "text").collect()]
    want = {i for i, (_, c) in _brute_groups(rows, 5, 80).items() if i == c}
    assert {r["doc_id"] for r in single.select("doc_id").collect()} == want and single.columns == docs.columns

    clean = corpus_pipeline.settle(corpus_pipeline.personal_data(spark, single, SMALL))
    assert clean.columns == docs.columns and clean.count() == single.count()
    email = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
    assert not any(email.search(r["text"]) for r in clean.select("text").collect())

    mix = corpus_pipeline.settle(corpus_pipeline.mixture(spark, clean, SMALL))
    assert mix.columns == docs.columns
    plan = curriculum.plan(clean).toPandas()
    assert sum(len(re.findall(r"[^\x20\x09-\x0D]+", r["text"])) for r in mix.select("text").collect()) == plan["taken"].sum()

    out = corpus_pipeline.encoding(spark, mix, SMALL)
    back = bpe_lookup.decode(spark, out, queries.tokenizer_path()).collect()
    have = sorted(hashlib.sha256(r["bytes"]).hexdigest() for r in back)
    assert have == sorted(hashlib.sha256(r["text"].encode()).hexdigest() for r in mix.select("text").collect())
    assert subword_quality.SAMPLE == 3000
