"""The corpus pipeline stage by stage."""

import re

import pytest

import corpus_pipeline
from cellfleet.llm import simhash

WORD = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="module")
def stages(spark, d):
    docs = spark.read.parquet(f"{d}/documents.parquet")
    out = [docs]
    for name, stage in corpus_pipeline.STAGES:
        out.append(corpus_pipeline.common.stored(stage(spark, out[-1], d), name))
    return out


def test_columns(stages):
    assert all(s.columns == stages[0].columns for s in stages[:-1])
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "simhash_near_dedup", "secret_scan", "mix_sources", "pack"]


def test_stages_take_effect(stages):
    docs, good, single, clean, mixed, packed = stages
    n = [s.count() for s in stages]
    assert 0.5 * n[0] < n[1] < n[0] and 0 < n[2] < n[1] and n[3] == n[2]
    texts = {r["doc_id"]: r["text"] for r in good.collect()}
    fps = {i: simhash.fingerprint(t) for i, t in texts.items()}
    kept = {r["doc_id"] for r in single.select("doc_id").collect()}
    near = {i: {j for j in fps if (fps[i] ^ fps[j]).bit_count() <= 3} for i in fps}
    left, groups = set(fps), []
    while left:
        group, new = set(), {left.pop()}
        while new:
            group |= new
            new = set().union(*(near[i] for i in new)) - group
        left -= group
        groups.append(group)
    assert kept == {min(g) for g in groups}
    assert clean.where("text rlike 'token = \"[0-9a-f]{40}\"'").count() == 0
    words = sum(len(WORD.findall(r["text"])) for r in clean.collect())
    assert abs(sum(len(WORD.findall(r["text"])) for r in mixed.collect()) - words) <= 20
    sums = packed.groupBy("sequence_id").sum("length").toPandas()["sum(length)"]
    assert sums.max() <= 1024


def test_empty(spark, d):
    docs = spark.read.parquet(f"{d}/documents.parquet").where("false")
    for name, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.common.stored(stage(spark, docs, d), name)
    assert docs.count() == 0
