"""The pipeline's stages against plain versions of the same decisions."""

import importlib
import pathlib

import pandas as pd
import pytest

import corpus_pipeline as cp
from mixedsketch.llm import quality_classifier
from mixedsketch.llm.workspace import Workspace
from tests.llm.test_operators import _contaminated, _joined

D = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def stages(spark):
    work, docs, out = Workspace(spark, "test"), spark.read.parquet(f"{D}/documents.parquet"), {}
    out["documents"] = docs.toPandas()
    for name, f in cp.STAGES:
        docs = work.save(f(spark, docs, D), name)
        out[name] = docs.toPandas()
    return out


def pairs(df):
    return [(int(i), t) for i, t in zip(df.doc_id, df.text, strict=True)]


def test_columns_and_order(stages):
    assert [n for n, _ in cp.STAGES] == ["quality", "near_duplicates", "decontamination", "pii", "packing"]
    for name in ("quality", "near_duplicates", "decontamination", "pii"):
        assert list(stages[name].columns) == cp.COLUMNS


def test_quality_keeps_what_scores_half(spark, stages):
    scores = quality_classifier.scored(spark.read.parquet(f"{D}/documents.parquet"), spark.read.parquet(f"{D}/labels.parquet")).toPandas()
    assert set(stages["quality"].doc_id) == set(scores[scores.score >= 0.5].doc_id)
    good = pd.read_parquet(f"{D}/labels.parquet").query("quality == 1").doc_id
    assert len(set(good) - set(stages["quality"].doc_id)) <= 2


def test_quality_keeps_all_without_a_model(spark, tmp_path):
    spark.createDataFrame([], "doc_id bigint, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    docs = spark.createDataFrame([(i, f"text {i}", "en", "s", 6) for i in range(5)], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    assert sorted(r["doc_id"] for r in cp.quality(spark, docs, str(tmp_path)).collect()) == list(range(5))


def test_one_of_each_group_stays(stages):
    want = {d for d, _, c in _joined(pairs(stages["quality"]), 5, 80) if d == c}
    assert sorted(stages["near_duplicates"].doc_id) == sorted(want)


def test_contaminated_documents_go(stages):
    items = [(int(i), t) for i, t in pd.read_parquet(f"{D}/benchmark.parquet")[["item_id", "text"]].itertuples(index=False)]
    want = {r[0] for r in _contaminated(pairs(stages["near_duplicates"]), items) if not r[5]}
    assert set(stages["decontamination"].doc_id) == want


def test_pseudonyms_keep_rows(stages):
    a, b = stages["decontamination"].set_index("doc_id"), stages["pii"].set_index("doc_id")
    assert set(a.index) == set(b.index) and (b.n_chars == b.text.str.len()).all()
    digits = a.text.str.contains(r"\d{16}|@|555-", regex=True)
    assert (a.text.reindex(b.index)[~digits.reindex(b.index)].str.len() > 0).all()
    assert (a.text[digits] != b.text.reindex(a.index)[digits]).all()


def test_all_documents_are_packed(stages):
    assert sorted(stages["packing"].doc_id) == sorted(stages["pii"].doc_id)


def test_near_duplicates_with_repeated_rows(spark):
    rows = [(5, "a b c d e f"), (5, "a b c d e f"), (6, "a b c d e f"), (7, ""), (7, None), (None, "x y")]
    docs = spark.createDataFrame([(i, t, "en", "s", 1) for i, t in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    assert sorted((r["doc_id"] for r in cp.near_duplicates(spark, docs, D).collect()), key=str) == [5, 7, None]


def test_rows_that_share_an_id_are_documents_of_their_own(spark, tmp_path):
    schema = "doc_id bigint, text string, lang string, source string, n_chars bigint"
    long = "one two three four five six seven eight nine ten eleven twelve"
    rows = [(1, long), (1, "quite another text with words of its own"), (None, long), (None, "only here is this sentence"), (None, "only here is this sentence"), (2, long), (3, " "), (3, None), (None, ""), (None, "")]
    docs = spark.createDataFrame([(i, t, "en", "s", 1) for i, t in rows], schema)
    got = sorted(((r["doc_id"], r["text"] or "") for r in cp.near_duplicates(spark, docs, D).collect()), key=str)
    assert [i for i, t in got if t.strip() == ""] == [3, None, None]
    assert [g for g in got if g[1].strip()] == sorted([(1, long), (1, rows[1][1]), (None, rows[3][1])], key=str)
    spark.createDataFrame([(9, "x " + long + " y")], "item_id bigint, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    left = sorted(((r["doc_id"], r["text"]) for r in cp.decontamination(spark, docs, str(tmp_path)).collect()), key=str)
    assert left == sorted([r for r in rows if r[1] != long], key=str)


def test_entry_without_these_folders(tmp_path, monkeypatch):
    """The driver's entry works when the corpus folders are gone."""
    import shutil
    import subprocess
    import sys

    top = pathlib.Path(cp.__file__).parent
    shutil.copy(top / "__spark_entry__.py", tmp_path)
    shutil.copytree(top / "mixedsketch", tmp_path / "mixedsketch", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    done = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()), 'pipeline' in e.queries())"], cwd=tmp_path, capture_output=True, text=True)
    assert done.returncode == 0 and done.stdout.split()[1] == "False", done.stderr
    assert importlib.util.find_spec("corpus_pipeline") is not None
