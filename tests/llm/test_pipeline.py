"""The pipeline stage by stage on a small folder of tables, against brute force."""

import corpus_pipeline
from layout_ie.llm import decontaminate, queries

from .data import TAIL, frame, prose
from .test_text_operators import components_by_hand, metrics_by_hand, print_by_hand


def write(spark, folder):
    item = prose(30, 500)
    docs = [(i, prose(70 + i % 5, i), "en", f"s{i % 3}", 1) for i in range(60)]
    docs += [(100, docs[3][1], "en", "s0", 1), (101, docs[4][1] + " more", "en", "s0", 1), (102, prose(60, 900) + " " + item, "en", "s1", 1), (103, "too short", "en", "s1", 1), (104, "again and again " * 50, "en", "s1", 1), (105, None, None, None, None)]
    docs = [(*d, *TAIL) for d in docs]
    frame(spark, docs).write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([(d[0], 1, 0) for d in docs[:40]], "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    spark.createDataFrame([(9, item)], "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
    return docs, [(9, item)]


def test_stages(spark, tmp_path):
    docs, items = write(spark, tmp_path)
    d = str(tmp_path)
    now = spark.read.parquet(f"{d}/documents.parquet")
    columns = now.columns
    text = {r[0]: r[1] for r in docs}
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "near_duplicates", "decontamination", "source_mixing", "token_store"]
    kept = {i for i, t in text.items() if (m := metrics_by_hand(t))[0] >= 50 and 2 * m[4] <= m[0]}
    for name, stage in corpus_pipeline.STAGES:
        now = stage(spark, now, d)
        if name != "token_store":
            assert now.columns == columns
            path = f"{d}/{name}"
            now.write.parquet(path)
            now = spark.read.parquet(path)
            ids = {r[0] for r in now.select("doc_id").collect()}
        if name == "near_duplicates":
            kept = set(components_by_hand({i: print_by_hand(text[i]) for i in kept}).values())
        if name == "decontamination":
            kept -= {r[0] for r in decontaminate.brute_force([(i, text[i]) for i in kept], items) if r[-1]}
        if name != "token_store":
            assert ids == kept, name
    rows = now.orderBy("start").collect()
    assert {r["doc_id"] for r in rows} == kept and [r["doc_id"] for r in rows] == sorted(r["doc_id"] for r in rows)
    assert sum(r["n_tokens"] for r in rows[:-1]) == rows[-1]["start"]


def test_empty_tables_and_null_ids(spark, tmp_path):
    """Every stage takes an empty table, and rows without an id come through."""
    docs, _ = write(spark, tmp_path)
    now = spark.read.parquet(f"{tmp_path}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, now.limit(0), str(tmp_path))
        assert out.count() == 0 and (name == "token_store" or out.columns == now.columns)
    lone = frame(spark, [(None, prose(90, 700 + i % 2), None, None, None, *TAIL) for i in range(4)])
    for name, stage in corpus_pipeline.STAGES:
        lone = stage(spark, lone, str(tmp_path))
    assert lone.count() == 4


def test_registered():
    assert sorted(int(n[2:].split("_")[0]) for n in queries.QUERIES) == list(range(1, 11))
