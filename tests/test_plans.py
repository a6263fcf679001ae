"""Physical plans stay what they are meant to be; the repository works without the corpus operators."""

import re
import shutil
import subprocess
import sys
from pathlib import Path

from trajkit.operators import features as FT, panel as P, rules
from trajkit.plans import QUERIES
from trajkit.plans.base_queries import panel_of

SF = "/root/testdata/sf0.001"
ROOT = Path(__file__).resolve().parent.parent


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_features_need_one_shuffle_and_no_python(spark):
    text = plan(FT.extract_features(panel_of(spark, SF, "part_quarter"), 28))
    exchanges = re.findall(r"Exchange hashpartitioning\((.*?), \d+\)", text)
    # Partial counts by item and period, then rows by item; every window and the last aggregate share it.
    assert len(exchanges) == 2 and "ArrowEval" not in text and "BatchEvalPython" not in text
    assert "ReadSchema: struct<l_partkey:bigint,l_shipdate:timestamp_ntz>" in text


def test_filters_reach_the_scan(spark):
    assert "PushedFilters: [IsNotNull(l_shipdate)" in plan(QUERIES["op_filter_range"](spark, SF))


def test_dimensions_are_broadcast_and_nothing_is_a_product(spark):
    assert plan(QUERIES["op_join_broadcast"](spark, SF)).count("BroadcastHashJoin") == 2
    assert "CartesianProduct" not in plan(QUERIES["w21_similar"](spark, SF))
    assert "Join" not in plan(P.densify(panel_of(spark, SF, "part_quarter"), 28))


def optimised(df) -> str:
    return df._jdf.queryExecution().optimizedPlan().toString()


def test_second_act_reads_a_series_once(spark):
    """The three periods are not put into each other's lambdas, which costs a power of the window."""
    series = spark.createDataFrame([(1, [1, 4, 1, 4])], "item_id long, series array<bigint>").repartition(2)
    text = optimised(rules.second_act(series, 4).select("item_id", "class"))
    assert text.count("array_max") == 1 and "filter(" not in text


def test_unclassified_share_builds_one_panel(spark):
    assert "lineitem" not in plan(QUERIES["unclassified_share"](spark, SF)) and QUERIES["w20_unclassified"] is QUERIES["unclassified_share"]


def test_worked_example_is_a_series_of_the_given_table(spark):
    r = QUERIES["w02_worked_example"](spark, SF).first()
    top = P.clip_window(panel_of(spark, SF, "part_quarter"), 8).groupBy("item_id").sum("n").collect()
    assert (r.item_id, r.total) == min(((i, c) for i, c in top), key=lambda x: (-x[1], x[0]))


def test_imports_without_the_corpus_operators(tmp_path):
    for p in ("trajkit", "__spark_entry__.py"):
        (shutil.copytree if (ROOT / p).is_dir() else shutil.copy)(ROOT / p, tmp_path / p)
    shutil.rmtree(tmp_path / "trajkit/llm", ignore_errors=True)
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 150 and 'pipeline' not in q and not any(k.startswith('op1_') for k in q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True)
    for f in (ROOT / "trajkit").rglob("*.py"):
        if "llm" not in f.parts:
            assert "trajkit.llm" not in f.read_text()
