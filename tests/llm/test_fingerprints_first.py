"""The pipeline's near-dedup goes by fingerprints first, and a crowd makes no rows by its square."""

import random

import pytest
from pyspark.sql import functions as F

from warpspan.llm import nearcopies, simhash

pipeline = pytest.importorskip("corpus_pipeline")


def _prose(rng, n):
    return [f"w{rng.randrange(5000)}" for _ in range(n)]


def test_fingerprints_in_reach_are_candidates(spark, sf, make_docs, monkeypatch):
    """A long text and a copy with its last word changed are a pair by fingerprints; the stage asks for it."""
    rng, asked = random.Random(4), []
    base = _prose(rng, 3000)
    docs = make_docs([" ".join(base), " ".join([*base[:-1], "other"]), " ".join(_prose(rng, 3000))])
    nodes = nearcopies.signed(docs, nearcopies.common_shingles(docs)).cache()
    fp = {r.doc_id: r.fp for r in nodes.collect()}
    assert {tuple(sorted(r)) for r in nearcopies.fingerprint_pairs(nodes).collect()} == {tuple(sorted((fp[1], fp[2])))}
    plain = docs.select("doc_id", simhash.fingerprint("text", nearcopies.WIDTH).alias("x"))
    assert {(r.doc_id, r.x) for r in plain.collect()} == {(r.doc_id, r.fingerprint) for r in nodes.collect()}
    near_pairs = simhash.near_pairs
    monkeypatch.setattr(simhash, "near_pairs", lambda prints, *more: asked.append(1) or near_pairs(prints, *more))
    assert {r.doc_id for r in pipeline.near_dedup(spark, docs, sf).collect()} == {1, 3} and asked


def test_a_crowd_of_texts_that_are_not_alike_makes_no_pairs(make_docs):
    """Sixty texts share half of their words, which stand in one key."""
    rng = random.Random(9)
    shared = _prose(rng, 100)
    docs = make_docs([" ".join(shared + _prose(rng, 100)) for _ in range(60)])
    nodes = nearcopies.signed(docs, nearcopies.common_shingles(docs))
    members = nodes.select(F.lit(1).alias("key"), "fp", F.col("fp").alias("root"), "n", "p0", "p1", "p2", "p3")
    assert nearcopies._every_pair(members).count() <= 60
