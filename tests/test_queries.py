"""Every registered query of the library against its DuckDB oracle."""

import pytest
from compare import same

from vecgraph.queries import ORACLES, QUERIES

# graph sizes at the smallest scale equal those at sf0.01, so these run on the same 500 vectors


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracle(spark, sf_dir, duck, name):
    same(QUERIES[name](spark, sf_dir), duck.sql(ORACLES[name]))


def test_entry(spark):
    import __spark_entry__

    df = __spark_entry__.entry(spark)
    assert df.columns == ["qid", "rank", "vid", "d2", "hops"] and df.count() == 100


def test_entry_without_llm(monkeypatch):
    import __spark_entry__

    monkeypatch.setattr(__spark_entry__, "_HAS_LLM", False)
    assert not [q for q in __spark_entry__.queries() if q.startswith("op")and q[2].isdigit()]
