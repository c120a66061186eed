import pytest

from pairmatch.catalog import library_oracles, library_queries
from tests.oracle import same

QUICK = ["pairs_w1", "pairs_w3", "pairs_w5", "ser_w1_right", "ser_w3_right", "ser_w4_left", "ser_w6_left", "ser_pair_input", "prompt_t1_hard", "prompt_t2_hard", "label_count_80", "blocking_quality", "asof_event_order", "json_props", "tumbling_events", "knowledge_tags_orders"]


def test_every_twin_has_a_query():
    assert set(library_oracles()) <= set(library_queries())


@pytest.mark.parametrize("name", QUICK)
def test_twin(spark, name):
    same(spark, library_queries()[name], library_oracles()[name])


def test_scores_and_selection_agree_with_sql(spark):
    same(spark, library_queries()["select_uncertainty_w1"], library_oracles()["select_uncertainty_w1"])


@pytest.mark.parametrize("name", ["prompt_soft_layout", "time_cut_proxy"])
def test_layouts_and_costs_come_from_the_tables(spark, name):
    same(spark, library_queries()[name], library_oracles()[name])


@pytest.mark.parametrize("name", ["select_random_w1", "select_confidence_w1"])
def test_selectors_that_need_no_passes_make_none(spark, monkeypatch, name):
    from pairmatch.operators.count_cloze import CountModel

    def none(*args, **kwargs):
        raise AssertionError("dropout passes")

    monkeypatch.setattr(CountModel, "passes", none)
    same(spark, library_queries()[name], library_oracles()[name])
