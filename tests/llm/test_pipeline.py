"""The pipeline on small tables against plain runs of the same rules."""

import collections

import duckdb
import pytest

from tests.llm import plain

pipeline = pytest.importorskip("corpus_pipeline")


def test_stages_and_run(spark, sf):
    from warpspan.llm import mixing, oracles, sharding

    assert [n for n, _ in pipeline.STAGES] == ["quality_rules", "near_dedup", "decontaminate", "mix_sources", "shard"]
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = {r.doc_id: r for r in docs.collect()}
    db = duckdb.connect()
    db.execute(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    kept = {i for i, good in db.execute(f"SELECT doc_id, kept FROM ({oracles.quality_rules()})").fetchall() if good}
    kept = set(plain.near_groups({i: rows[i].text for i in kept}).values())
    items = [r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    kept = {i for i in kept if not plain.contaminated(rows[i].text, items)[2]}
    left = docs.where(docs.doc_id.isin(*kept))
    wanted = collections.Counter(r.doc_id for r in mixing.schedule(left).collect())  # held against a plain run in its own test
    out = pipeline.run(spark, sf)
    assert out.columns == docs.columns + ["shard", "slot"]
    found = out.collect()
    assert collections.Counter(r.doc_id for r in found) == wanted and set(wanted) == kept
    assert all(r.text == rows[r.doc_id].text and r.source == rows[r.doc_id].source for r in found)
    shards = collections.defaultdict(list)
    for r in found:
        shards[r.shard].append(r.slot)
    sizes = [len(shards[k]) for k in range(sharding.SHARDS)]
    assert max(sizes) - min(sizes) <= 1 and all(sorted(slots) == list(range(len(slots))) for slots in shards.values())
    cells = {r.doc_id: r._cell for r in sharding.with_cell(left).collect()}
    order = [cells[r.doc_id] for r in sorted(found, key=lambda r: (r.shard, r.slot))]
    assert order == sorted(order)


def test_empty_and_null_documents(spark, sf):
    empty = spark.read.parquet(f"{sf}/documents.parquet").where("false")
    null = spark.createDataFrame([(None, None, None, None, None), (1, None, None, None, None)], empty.schema)
    for docs in (empty, null):
        for _, stage in pipeline.STAGES:
            docs = stage(spark, docs, sf)
        assert docs.count() == 0


def test_clashing_names_and_nulls_pass_through(spark, sf, clashing):
    names, clashing = clashing.columns, clashing.where("text is null or length(text) < 3000")
    for name, stage in pipeline.STAGES[1:]:
        out = stage(spark, clashing, sf)
        assert out.columns == (names if name != "shard" else [*names, "shard", "slot"])
        assert 0 < out.count()
