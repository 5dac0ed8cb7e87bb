"""Queries of many settings: what one setting wrote is gone when the next is run, and its pairs are counted."""

import pytest
from conftest import MEDIUM, SMALL
from oracle import connect, same

from rareblock.plans import storage
from rareblock.workloads import comparing


@pytest.mark.parametrize("name,most", [("sensitivity_part", 10), ("ablate_lsh_pages", 9), ("ablate_lsh_docs", 9)])
def test_settings_leave_a_row(spark, name, most):
    before = {path for _, path in storage._written}
    found = comparing.QUERIES[name](spark, SMALL)
    left = [path for _, path in storage._written if path not in before]
    assert len(left) <= most, left  # a table per setting and what all of them read
    assert found.count() == 8


@pytest.mark.parametrize("name", ["ablate_lsh_docs", "ablate_lsh_pages"])
def test_banded_settings_lay_out_no_pair(spark, monkeypatch, name):
    made = []
    monkeypatch.setattr(comparing, "_rib", lambda index, name, do=comparing._rib: made.append(name) or do(index, name))
    same(comparing.QUERIES[name](spark, MEDIUM), connect(MEDIUM), comparing.ORACLE_SQL[name])
    assert made == ["lsh"]  # identity keys
