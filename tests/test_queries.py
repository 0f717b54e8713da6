"""Every registered query of the engine runs, and equals its SQL where it has one."""

from __future__ import annotations

import pytest

from tests_oracle import connect, differs
from unioncount.registry import ORACLES, QUERIES


@pytest.fixture(scope="module")
def con(smoke_dir):
    return connect(smoke_dir)


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(spark, smoke_dir, con, name):
    df = QUERIES[name](spark, smoke_dir)
    if name in ORACLES:
        assert differs(df, con, ORACLES[name]) == ""
    else:
        assert df.columns and df.count() > 0


def test_stream_join_is_repeatable(spark, smoke_dir, con):
    for _ in range(3):
        assert differs(QUERIES["stream_stream_join"](spark, smoke_dir), con, ORACLES["stream_stream_join"]) == ""


def test_builtin_estimates_are_near(spark, smoke_dir):
    r = QUERIES["builtin_estimates"](spark, smoke_dir).first()
    assert all(abs(x - r.n_true) < 0.1 * r.n_true for x in (r.approx, r.hll, r.theta))


def test_noise_from_the_system(spark, smoke_dir):
    r = QUERIES["noise_from_os"](spark, smoke_dir).collect()
    assert len({x.holder for x in r}) == len(r) and all(abs(x.noise) < 30 for x in r)


def test_samples_are_parts(spark, smoke_dir):
    r = QUERIES["sample_rows"](spark, smoke_dir).groupBy("o_orderstatus").count().collect()
    assert {x.o_orderstatus for x in r} == {"F", "O"} and all(10 < x["count"] < 300 for x in r)


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 1
    assert set(e.oracle_sql()) <= set(e.queries())
