"""Shapes of physical plans."""

import __spark_entry__ as entry
import pytest


def plan(spark, small, name):
    return entry.queries()[name](spark, small)._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", ["publisher_retain", "rating_map"])
def test_short_lists_are_broadcast(spark, small, name):
    p = plan(spark, small, name)
    assert "BroadcastHashJoin" in p and "SortMergeJoin" not in p


@pytest.mark.parametrize("name", ["appearance_cap2", "media_cap4", "split_balanced"])
def test_limits_reach_below_the_shuffle(spark, small, name):
    assert "WindowGroupLimit" in plan(spark, small, name)


@pytest.mark.parametrize("name", ["verdict_integrity", "evidence_admissible", "media_dedup", "cutoff_curve", "cutoff_inflation"])
def test_no_pairs_of_everything(spark, small, name):
    p = plan(spark, small, name)
    assert "CartesianProduct" not in p and "BroadcastNestedLoopJoin" not in p


@pytest.mark.parametrize("name", ["article_clean", "claim_validate", "language_identify_accuracy", "verdict_integrity", "ensemble_mean"])
def test_no_python(spark, small, name):
    p = plan(spark, small, name)
    assert "Python" not in p and "Arrow" not in p


def test_scans_are_narrow(spark, small):
    p = plan(spark, small, "verdict_integrity")
    assert "l_extendedprice" not in p and p.count("Exchange hashpartitioning") <= 3


@pytest.mark.parametrize(("name", "exchanges"), [("ensemble_agreement", 1), ("human_eval_ablations", 4)])
def test_scorers_see_each_text_once(spark, small, name, exchanges):
    """Every text is searched for symbols once and split once for words; votes of one claim need no shuffle."""
    p = plan(spark, small, name)
    assert p.count("regexp_replace(") == 1 and p.count("array_distinct(") == 2
    assert p.count("Exchange") - p.count("BroadcastExchange") - p.count("ReusedExchange") <= exchanges


def test_search_shuffles_no_pairs(spark, small):
    """Documents are dealt once; pairs are summed where they are, and only the best of each partition leave it."""
    p = plan(spark, small, "evidence_search")
    assert "WindowGroupLimit" in p and "hashpartitioning(claim_id" in p
    assert "hashpartitioning(claim_id#" in p and not any("doc_id" in line and "claim_id" in line for line in p.splitlines() if "Exchange hashpartitioning" in line)
