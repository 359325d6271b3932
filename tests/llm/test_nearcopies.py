"""Near copies against the Jaccard similarity of every pair."""

import random
import time

import numpy as np
import pytest

from warpspan.llm import common, nearcopies, simhash

pipeline = pytest.importorskip("corpus_pipeline")


def _set(text):
    words = (text or "").encode().lower().split()
    return {tuple(words[k : k + 5]) for k in range(max(1, len(words) - 4))}


def _groups(texts):
    sets = [_set(t) for t in texts]
    root = list(range(len(texts)))
    for b in range(len(texts)):
        for a in range(b):
            if 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
                old, new = root[b], root[a]
                root = [min(old, new) if r in (old, new) else r for r in root]
    return {i + 1: r + 1 for i, r in enumerate(root)}


@pytest.fixture(scope="module")
def edited():
    """Edited copies with 1 to 12 changes, a family of forty, a line that all share, and odd texts."""
    rng = random.Random(11)
    words = [f"w{k}" for k in range(900)]
    prose = lambda n: [rng.choice(words) for _ in range(n)]

    def edit(base, times):
        out = list(base)
        for _ in range(times):
            at = rng.randrange(len(out))
            out[at : at + rng.randint(0, 1)] = [rng.choice(words)]
        return " ".join(out)

    line = " ".join(prose(14))
    out = [None, "", "one two", "One two"]
    for size in (60, 120, 300):
        for _ in range(8):
            base = prose(size)
            out += [" ".join(base), edit(base, rng.randint(1, 3)), edit(base, rng.randint(2, 12))]
    family = prose(150)
    out += [edit(family, rng.randint(1, 4)) + " " + line for _ in range(40)]
    out += [" ".join(prose(rng.randint(20, 60))) + " " + line for _ in range(40)]
    rng.shuffle(out)
    return out


@pytest.mark.parametrize("few", [24, 3])
def test_groups_are_those_of_every_pair(make_docs, edited, few):
    found = {r.doc_id: r.component_id for r in nearcopies.classify(make_docs(edited), few=few).collect()}
    assert found == _groups(edited)


def test_stage_keeps_one_of_each_group(spark, sf, make_docs, edited):
    left = pipeline.near_dedup(spark, make_docs(edited), sf)
    assert {r.doc_id for r in left.collect()} == set(_groups(edited).values())


def test_order_of_common_shingles_changes_nothing(make_docs, edited, monkeypatch):
    monkeypatch.setattr(nearcopies, "COUNTED", 1)
    assert len(nearcopies.common_shingles(make_docs(edited))) > 0
    found = {r.doc_id: r.component_id for r in nearcopies.classify(make_docs(edited)).collect()}
    assert found == _groups(edited)


def test_parity_maps_never_exceed_the_difference():
    rng = random.Random(2)
    for _ in range(200):
        a = np.unique(np.array([rng.getrandbits(64) for _ in range(rng.randint(0, 400))], dtype=np.uint64))
        b = np.unique(np.concatenate([a[rng.randint(0, 20) :], np.array([rng.getrandbits(64) for _ in range(rng.randint(0, 60))], dtype=np.uint64)]))
        differ = np.bitwise_count((nearcopies.parity_map(a) ^ nearcopies.parity_map(b)).view(np.uint64)).sum()
        assert differ <= len(np.setxor1d(a, b))


def _shuffle_files(spark):
    """Data files of shuffles on the session's disk."""
    found = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    names = [found.apply(k).getName() for k in range(found.size())]
    return {n for n in names if n.startswith("shuffle_") and n.endswith(".data")}


def test_written_tables_leave_no_shuffle_files(spark):
    """They stayed until the driver collected its garbage, and rounds of small tables filled the disk."""
    from pyspark.sql import functions as F

    from warpspan.llm.common import cut

    frame = spark.range(5000).groupBy((F.col("id") % 997).alias("k")).count()
    before = _shuffle_files(spark)
    made = cut(frame)
    for _ in range(50):  # they go in the background
        if _shuffle_files(spark) <= before:
            break
        time.sleep(0.2)
    assert _shuffle_files(spark) <= before
    frame.write.format("noop").mode("overwrite").save()
    assert _shuffle_files(spark) - before  # what is not written by cut keeps them
    assert made.count() == 997


def _links():
    """A long chain, stars around the largest and the smallest node, random links and repeats, over the whole range of nodes."""
    rng = random.Random(3)
    nodes = list(dict.fromkeys(rng.getrandbits(64) - (1 << 63) for _ in range(900)))
    chain = list(zip(nodes[:200], nodes[1:200], strict=False))
    high, low = sorted(nodes[200:300]), sorted(nodes[300:400])
    stars = [(high[-1], x) for x in high[:-1]] + [(low[0], x) for x in low[1:]]
    some = [tuple(rng.sample(nodes[400:], 2)) for _ in range(260)]
    return [*chain, *stars, *some, *some[:20], (nodes[0], nodes[0])]


def test_components_of_few_links_take_few_stages(spark):
    """Each round of contraction took eight stages for a handful of rows."""
    links = _links()
    root = {}
    for a, b in links:
        x, y = root.setdefault(a, a), root.setdefault(b, b)
        root = {k: min(x, y) if r in (x, y) else r for k, r in root.items()}
    wanted = {k: r for k, r in root.items() if k != r}
    frame = spark.createDataFrame(links, "a bigint, b bigint")
    stage = lambda: spark.sparkContext._jsc.sc().dagScheduler().nextStageId()
    before = stage()
    found = simhash.components(frame)
    assert stage() - before <= 6
    assert {r.node: r.root for r in found.collect()} == wanted
    assert {r.node: r.root for r in simhash.components(frame, most_collected=100).collect()} == wanted
    assert simhash.components(frame.where("false")).count() == 0


def test_groups_are_the_same_by_contraction(make_docs, edited, monkeypatch):
    whole = simhash.components
    monkeypatch.setattr(simhash, "components", lambda links: whole(links, most_collected=0))
    found = {r.doc_id: r.component_id for r in nearcopies.classify(make_docs(edited), few=3).collect()}
    assert found == _groups(edited)


def test_near_dedup_deletes_what_it_used(make_docs, edited):
    """Nodes with their prefixes, candidates and sets stayed on disk through the later stages."""
    mark = common.written_so_far()
    kept = nearcopies.keep_one(make_docs(edited))
    wide = [p for p in common._written[mark:] if {"keys", "hashes", "p0"} & set(kept.sparkSession.read.parquet(p).columns)]
    assert not wide
    assert {r.doc_id for r in kept.collect()} == set(_groups(edited).values())
