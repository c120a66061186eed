from collections import Counter

import pytest

from pairmatch.catalog import library_queries
from pairmatch.record_queries import oracles, queries
from pairmatch.sources import workloads as W
from tests.oracle import same


@pytest.mark.parametrize("name", sorted(set(oracles()) & set(queries())) + ["pairs_w10"])
def test_twin(spark, name):
    same(spark, library_queries()[name], oracles()[name])


def test_ranks_do_not_depend_on_ranges(spark, monkeypatch):
    rows = spark.createDataFrame([(f"r{i}", i, "one" if i % 7 else "two") for i in range(700)], "id string, key int, block string")
    want = {(r.id, r["rank"]) for r in W.numbered(rows)[0].collect()}
    monkeypatch.setattr(W, "CELL_ROWS", 40)
    ranked, sizes = W.numbered(rows)
    assert {(r.id, r["rank"]) for r in ranked.collect()} == want
    assert {r.block: r.size_ for r in sizes.collect()} == {"one": 600, "two": 100}
    assert sorted(r["rank"] for r in ranked.where("block = 'one'").collect()) == list(range(600))


def test_a_left_record_meets_ten_others_at_most(spark):
    found = W.pairs(spark, "/root/testdata/sf0.001", "w6").collect()  # one block of all rows
    assert max(Counter(r.left_id for r in found).values()) <= 10
    assert {r.left_id for r in found if r.y == 1} == {r.left_id for r in found}
    assert len({r.pair_id for r in found}) == len(found)
