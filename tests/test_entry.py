"""Queries against their SQL on the smallest tables, and what must hold without the llm subpackage."""

import os
import shutil
import subprocess
import sys
from pathlib import Path

import duckdb
import pytest

import __spark_entry__ as entry

REPO = Path(__file__).resolve().parents[1]
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: One of each family; the driver compares all of them.
CHECKED = ["corpus_revisit_en", "book_revisit", "browse_sessions", "tutor_feedback", "tutor_asof", "lm_kneser_ney", "select_topk", "render_marked", "word_pool", "mc_items", "rq1_within_word", "rq3_overhead", "guess_moments", "tutor_quiz", "select_rescored", "snippet_cover", "guess_rank"]


def plain(v):
    return round(v, 6) + 0.0 if isinstance(v, float) else v


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_sql(spark, smoke, name):
    df = entry.queries()[name](spark, smoke)
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from read_parquet('{smoke}/{t}.parquet')")
    want = con.sql(entry.oracle_sql()[name])
    names = sorted(want.columns)
    assert names == sorted(df.columns)
    at = [want.columns.index(c) for c in names]
    assert sorted(repr(tuple(plain(r[c]) for c in names)) for r in df.collect()) == sorted(repr(tuple(plain(r[i]) for i in at)) for r in want.fetchall())


def test_flagship_has_rows(spark):
    assert entry.entry(spark).count() > 0


def test_oracles_belong_to_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def without_llm(to):
    """A copy of the repository's core, as it is when the subpackage, its tests and the pipeline have been deleted."""
    shutil.copytree(REPO / "embedvocab", to / "embedvocab", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copytree(REPO / "tests", to / "tests", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(REPO / "__spark_entry__.py", to)


def test_core_imports_without_llm(tmp_path):
    """The entry module and all other queries stay."""
    without_llm(tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert 'corpus_revisit_en' in q and not any(n.startswith('op') for n in q), q"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True)


@pytest.mark.skipif(bool(os.environ.get("EMBEDVOCAB_NESTED")), reason="runs within the copy")
def test_core_suite_passes_without_llm(tmp_path):
    without_llm(tmp_path)
    run = subprocess.run([sys.executable, "-m", "pytest", "tests", "-x", "-q"], cwd=tmp_path, env=os.environ | {"EMBEDVOCAB_NESTED": "1"}, capture_output=True, text=True)
    assert run.returncode == 0, run.stdout[-3000:]
