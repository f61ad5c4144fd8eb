"""The corpus pipeline against a brute-force version of its stages, and on odd tables."""

import subprocess
import sys
from collections import defaultdict
from pathlib import Path

import pytest
from conftest import SF
from test_nearcopies import brute_kept
from test_operators import ROWS, lower, worded

import corpus_pipeline as cp
from dpsynth.llm import bpe


def test_pipeline_equals_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = {r["doc_id"]: r["text"] for r in cp.identify_language(spark, docs, SF).collect()}
    assert len(kept) >= 0.98 * docs.count()
    lines = defaultdict(set)
    key = lambda x: lower(x).strip(" \t\n\x0b\x0c\r")
    for i, t in kept.items():
        for x in t.split("\n"):
            lines[key(x)].add(i)
    kept = {i: "\n".join(x for x in t.split("\n") if not key(x) or len(lines[key(x)]) < 10) for i, t in kept.items()}
    first = brute_kept(kept)
    kept = {i: t for i, t in kept.items() if i in first}
    windows = set()
    for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect():
        w = worded(r["text"])
        windows |= {tuple(w[i : i + min(10, len(w))]) for i in range(max(1, len(w) - 9)) if w}
    sizes = {len(w) for w in windows}

    def dirty(text):
        w = worded(text)
        return any(tuple(w[i : i + n]) in windows for n in sizes for i in range(len(w) - n + 1))

    kept = {i: t for i, t in kept.items() if not dirty(t)}
    out = {r["doc_id"]: r for r in cp.run(spark, SF).collect()}
    assert {i: r["text"] for i, r in out.items()} == kept
    coder = bpe.coder()
    for i, r in out.items():
        assert r["token_ids"] == coder.encode(kept[i]) and r["n_chars"] == len(kept[i])


#: Extra columns with names that operators use inside.
EXTRA = {"llm_key": 1, "llm_row": "r", "llm_hash": 2.5, "llm_doc": "d", "llm_n": 7, "llm_bits": "b", "llm_words": "w", "llm_spans": "MINE", "llm_items": 4, "lang_pred": "MINE", "score": -7.0,
         "llm_best": 1, "llm_top": 2, "llm_n_lines": "n", "fp": 3, "key": 5, "none": 6, "row": 8, "h1": "h", "llm_all": 0}
NAMES = ["doc_id", "text", "lang", "source", "n_chars", *EXTRA]


def odd_table(spark, rows):
    kind = lambda v: {int: "long", float: "double", str: "string"}[type(v)]
    schema = "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{n}` {kind(v)}" for n, v in EXTRA.items())
    return spark.createDataFrame([(*r, *EXTRA.values()) for r in rows], schema)


def test_stages_on_odd_tables(spark, tmp_path):
    docs = odd_table(spark, ROWS)
    for k, (_, stage) in enumerate(cp.STAGES):
        out = stage(spark, docs, SF)
        assert out.columns == [*NAMES, *(["token_ids"] if k == len(cp.STAGES) - 1 else [])]
        assert stage(spark, docs.limit(0), SF).count() == 0
        out.write.parquet(str(tmp_path / str(k)))
        docs = spark.read.parquet(str(tmp_path / str(k)))
        rows = [r.asDict() for r in docs.collect()]
        assert rows and all({n: r[n] for n in EXTRA} == EXTRA for r in rows)
        given = {(r[0], r[2], r[3]) for r in ROWS}
        assert all((r["doc_id"], r["lang"], r["source"]) in given for r in rows)


@pytest.mark.parametrize(("k", "want"), [(0, None), (1, 12), (2, None), (3, 12), (4, 12)])
def test_null_empty_and_repeated_texts(spark, k, want):
    """What each stage's docstring says of the odd rows."""
    rows = [r.asDict() for r in cp.STAGES[k][1](spark, odd_table(spark, ROWS), SF).collect()]
    ids = sorted(r["doc_id"] or -1 for r in rows)
    if want:
        assert len(rows) == want
    if k == 0:
        assert not {3, 4, 5, 7} & set(ids) and ids.count(1) == 2
    if k == 1:
        assert all(r["text"] is not None and r["n_chars"] == len(r["text"]) for r in rows)
    if k == 2:  # null first: the rows of null id and null text, and of one line, are the first of their groups
        assert ids.count(1) == 1 and ids.count(-1) == 2 and not {3, 4, 5} & set(ids)
    if k == 4:
        assert all(r["token_ids"] == [] for r in rows if not r["text"])


def test_copies_leave_one(spark):
    words = [f"w{i}" for i in range(60)]
    near, far = " ".join([*words[:-1], "x"]), " ".join(f"v{i}" for i in range(60))
    docs = spark.createDataFrame([(i, " ".join(words), "en", "s", 9) for i in (5, 3, 9)] + [(7, near, "en", "s", 9), (8, far, "en", "s", 9)], "doc_id long, text string, lang string, source string, n_chars long")
    assert {r["doc_id"] for r in cp.dedup_documents(spark, docs, SF).collect()} == {3, 8}


def test_workers_need_no_copy_of_the_package(tmp_path):
    """All operators and the pipeline where only the driver can import the package."""
    root = Path(__file__).resolve().parents[2]
    script = f"""
import sys
sys.path.insert(0, {str(root)!r})
from pyspark.sql import SparkSession
spark = SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.checkpoint.dir", {str(tmp_path / "c")!r}).getOrCreate()
spark.sparkContext.setLogLevel("OFF")

def imports(_):
    try:
        import dpsynth
    except ImportError:
        return [False]
    return [True]

assert spark.sparkContext.parallelize([0], 1).flatMap(imports).collect() == [False]
import corpus_pipeline
from dpsynth.llm import registry
for name, run in (registry.queries() | {{"pipeline": corpus_pipeline.run}}).items():
    assert run(spark, {SF!r}).toPandas().shape[0] > 0, name
print("all ran")
"""
    (tmp_path / "script.py").write_text(script)
    out = subprocess.run([sys.executable, "script.py"], cwd=tmp_path, capture_output=True, text=True, timeout=600, env={k: v for k, v in __import__("os").environ.items() if k != "PYTHONPATH"})
    assert "all ran" in out.stdout, out.stderr[-3000:]
