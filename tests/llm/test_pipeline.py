"""The pipeline's stages against plain versions of their rules."""

from __future__ import annotations

from pathlib import Path

import pytest
from pyspark.sql import functions as F

pipeline = pytest.importorskip("corpus_pipeline") if (Path(__file__).resolve().parents[2] / "corpus_pipeline.py").exists() else pytest.skip("no pipeline", allow_module_level=True)


def test_stages_take_effect(spark, sf):
    from litspark.llm import decontamination, near_dedup, quality_rules, secret_scan

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    seen, rows = docs, {}
    for name, stage in pipeline.STAGES[:-1]:
        out = stage(spark, seen, sf).persist()
        assert out.columns == docs.columns
        rows[name] = (seen, out)
        seen = out
    before, after = rows["quality"]
    kept = quality_rules.quality_verdicts(before).where("kept").select("doc_id")
    assert sorted(after.select("doc_id").collect()) == sorted(kept.collect())
    before, after = rows["near_dedup"]
    assert sorted(after.select("doc_id").collect()) == sorted(near_dedup.near_duplicates(before).where("kept").select("doc_id").collect())
    before, after = rows["decontaminate"]
    bench = spark.read.parquet(f"{sf}/benchmark.parquet")
    assert after.count() == before.count() - decontamination.leaks(before, bench).select("doc_id").distinct().count()
    said = [r.text for r in bench.collect()]
    assert not any(s in r.text for r in after.collect() for s in said)
    before, after = rows["secrets"]
    assert after.count() == before.count()
    assert after.where(F.lower("text").rlike('token = "[0-9a-f]{40}')).count() == 0
    assert after.where("n_chars <> length(text)").count() == before.where("n_chars <> length(text)").count()
    assert secret_scan.secret_report(after).where("n_findings > 0").count() == 0
    last = pipeline.run(spark, sf)
    assert sorted(last.select("doc_id").collect()) == sorted(after.select("doc_id").collect())
    assert last.where("n_tokens <> size(ids)").count() == 0


def test_edge_rows_pass_every_stage(spark, sf, tmp_path):
    good = [(i, f"Some words of document {i} that are all its own: " + " ".join(f"w{i}x{j}" for j in range(40)), "en", "s", 1) for i in range(20)]
    odd = [(None, None, None, None, None), (None, good[0][1] + " no id", "en", "s", 1), (50, "", "en", "s", 0), (3, good[3][1], "en", "s", 1), (3, good[4][1] + " an id twice", "en", "s", 1), (60, "x " * 50_000, "en", None, 1)]
    docs = spark.createDataFrame(good + odd, "doc_id long, text string, lang string, source string, n_chars long")
    clash = ["pick", "tag", "_pick", "_tag", "judged", "candidates", "findings", "redacted", "key", "node", "component", "kept", "Grp", "row"]
    docs = docs.withColumns({c: F.concat(F.lit(c), F.col("doc_id").cast("string")) for c in clash}).repartition(3)
    for name, stage in pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns and out.schema == docs.schema, name
        rows = out.collect()
        assert all(r[c] is None if r.doc_id is None else r[c] == f"{c}{r.doc_id}" for r in rows for c in clash)
        assert {r.doc_id for r in rows} >= set(range(20)) - {4}  # 4 has a near copy under a smaller id
        assert stage(spark, docs.limit(0), sf).count() == 0
    assert pipeline.STAGES[-1][1](spark, docs, sf).count() == len(good + odd)
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    spark.read.parquet(f"{sf}/benchmark.parquet").write.parquet(str(tmp_path / "benchmark.parquet"))
    assert {r.doc_id for r in pipeline.run(spark, str(tmp_path)).collect()} >= set(range(20)) - {4}
