"""The driver's contract, plans, and a sample of queries against DuckDB at the smallest size."""

import math
import subprocess
import sys

import duckdb
import pytest

import __spark_entry__ as entry
from approxmatch import catalog
from approxmatch.operators import ranking, scoring
from approxmatch.operators.index import TokenIndex, TokenSpec, tokenized
from approxmatch.plans import planner
from approxmatch.sources import tables

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SAMPLE = [
    "tok_qgram3", "stat_terms", "w_lm_prob", "sim_bm25", "sim_lm_full", "sim_wj_rs", "sim_cosine_word", "sel_edit_07", "sel_edit_04_vacuous", "sim_ges_jaccard",
    "sim_soft_edit", "join_jaccard", "prune_02_bm25", "eval_map", "gen_swap", "op_asof", "op_join_range", "op_win_frame", "fn_array", "sql_front", "stream_sessions", "stream_dedup",
]


def norm(v):
    if isinstance(v, list | tuple):
        return tuple(map(norm, v))
    if hasattr(v, "as_tuple"):
        v = float(v)
    return round(v, 5) if isinstance(v, float) and math.isfinite(v) else v


@pytest.mark.parametrize("name", SAMPLE)
def test_equals_duckdb(spark, sf, name):
    df = entry.queries()[name](spark, sf)
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    r = c.execute(entry.oracle_sql()[name])
    at = [[x[0] for x in r.description].index(k) for k in df.columns]
    want = sorted((tuple(norm(row[i]) for i in at) for row in r.fetchall()), key=repr)
    assert sorted((tuple(map(norm, row)) for row in df.collect()), key=repr) == want


def test_entry(spark):
    rows = entry.entry(spark).collect()
    assert len(rows) == 10 and rows[0].asDict().keys() == {"qid", "tid", "score"}


def test_oracles_have_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_without_the_corpus_operators(tmp_path):
    """The rest imports and lists its queries where the llm folders and the pipeline were taken away."""
    import shutil
    from pathlib import Path

    root = Path(entry.__file__).parent
    shutil.copy(root / "__spark_entry__.py", tmp_path)
    shutil.copytree(root / "approxmatch", tmp_path / "approxmatch", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    code = "import __spark_entry__ as e; q = e.queries(); assert 'sim_bm25' in q and 'pipeline' not in q and not any(k.startswith('op1_') for k in q); e.oracle_sql()"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env={"PATH": "/usr/bin", "PYTHONPATH": str(tmp_path)}, check=True)


def plan(df):
    return planner.explain(df).split("== Physical Plan ==")[1]


def test_plans(spark, sf):
    index = TokenIndex.build(tables.part_desc(spark, sf))
    bm25 = plan(scoring.score_bm25(index, "hot gear"))
    assert "BroadcastHashJoin" in bm25 and "CartesianProduct" not in bm25 and "Python" not in bm25 and "ArrowEval" not in bm25
    assert "p_name" not in bm25 and "ReadSchema: struct<tid:bigint,bag:" in bm25  # the stored index: strings aren't tokenised again
    built = plan(tokenized(tables.part_desc(spark, sf), TokenSpec()))
    assert built.count("regexp_replace") == 1 and "ReadSchema: struct<p_partkey:bigint,p_name:string,p_brand:string,p_type:string>" in built
    assert "TakeOrderedAndProject" in plan(ranking.approx_select(index, "hot gear", "bm25", k=5))
    assert "WindowGroupLimit" in plan(ranking.approx_select(index, [(1, "hot"), (2, "gear")], "bm25", k=5))
    row = plan(scoring.score_bm25(index, "hot gear", layout="row"))
    assert "SortMergeJoin" not in row
    chosen = planner.choose_plan(index, "hot gear")
    assert chosen.layout in scoring.LAYOUTS and chosen.touched > 0
    assert catalog.flagship(spark, sf).count() == 10
