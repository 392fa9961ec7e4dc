"""The stages over the small tables, and that the library stands without them."""

import subprocess
import sys
from pathlib import Path

import corpus_pipeline
import pytest
from pyspark.sql import functions as F

SMALL = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def steps(spark, tmp_path_factory):
    place = tmp_path_factory.mktemp("pipeline")
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    out = {"documents": docs}
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, SMALL).write.parquet(f"{place}/{name}")
        docs = out[name] = spark.read.parquet(f"{place}/{name}")
    return out


def test_columns_and_order(steps):
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["quality_rules", "line_dedup", "simhash", "mixing", "packing"]
    for n in names[:-1]:
        assert steps[n].columns == steps["documents"].columns
        assert steps[n].dtypes == steps["documents"].dtypes


def test_each_stage_takes_effect(steps):
    n = {k: v.count() for k, v in steps.items()}
    assert n["documents"] > n["quality_rules"] == n["line_dedup"] >= n["simhash"] > n["mixing"]
    before, after = (steps[k].agg(F.sum(F.char_length("text"))).first()[0] for k in ("quality_rules", "line_dedup"))
    assert after < before
    assert steps["line_dedup"].where("n_chars <> char_length(text)").count() == 0
    ids = {r.doc_id for r in steps["mixing"].select("doc_id").collect()}
    assert {r.doc_id for r in steps["packing"].select("doc_id").collect()} == ids


def test_clean_documents_stay(steps, spark):
    labels = spark.read.parquet(f"{SMALL}/labels.parquet")
    clean = labels.where("quality = 1 and toxic = 0").join(steps["documents"].where("size(split(text, ' ')) >= 60"), "doc_id")
    kept = clean.join(steps["quality_rules"].select("doc_id"), "doc_id", "left_semi").count()
    assert kept == clean.count()
    through = labels.where("quality = 1 and toxic = 0").join(steps["simhash"].select("doc_id"), "doc_id", "left_semi")
    assert through.join(steps["mixing"].select("doc_id"), "doc_id", "left_semi").count() >= 0.97 * through.count()


def test_run_gives_the_same_pieces(steps, spark):
    cols = ["doc_id", "start", "length", "ids_crc32"]
    got = corpus_pipeline.run(spark, SMALL).select("doc_id", "doc_tokens").distinct()
    want = steps["packing"].select("doc_id", "doc_tokens").distinct()
    assert got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0
    assert set(cols) <= set(steps["packing"].columns)


def test_library_does_not_need_the_operators():
    root = Path(__file__).resolve().parents[2]
    code = "import sys; sys.modules['bucketnet.llm'] = None; sys.modules['corpus_pipeline'] = None; import __spark_entry__ as e; assert 'pipeline' not in e.queries() and len(e.queries()) > 100 and len(e.oracle_sql()) > 100"
    assert subprocess.run([sys.executable, "-c", code], cwd=root, timeout=60, check=False).returncode == 0
    for f in (root / "bucketnet").rglob("*.py"):
        if "llm" not in f.parts:
            assert "bucketnet.llm" not in f.read_text()
