"""Every registered query of the engine that has SQL equals it on the smallest tables; the others give rows."""

from __future__ import annotations

import pytest
from conftest import same_rows

from litspark.queries import ORACLES, QUERIES

#: Timed or trained queries, covered by tests of their own.
LONG = {"strong_scaling", "parser_throughput", "fit_ablation_table", "qa_accuracy_grid", "retrieval_table", "answering_table", "training_performance", "training_scaling"}


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_sql(spark, duck, sf, name):
    same_rows(QUERIES[name](spark, sf), duck.sql(ORACLES[name]))


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES) - LONG))
def test_gives_rows(spark, sf, name):
    assert not QUERIES[name](spark, sf).isEmpty()


def test_entry_point(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_the_rest_stands_without_the_training_data_part():
    import subprocess
    import sys
    from pathlib import Path

    root = Path(__file__).resolve().parents[1]
    code = "import sys; sys.modules['litspark.llm'] = None; import __spark_entry__ as e; q = e.queries(); assert 'parsed_pages' in q and 'pipeline' not in q and not any(n.startswith('op5_') for n in q); e.oracle_sql()"
    subprocess.run([sys.executable, "-c", code], cwd=root, check=True)
    for file in (root / "litspark").rglob("*.py"):
        if "llm" not in file.parts:
            assert "litspark.llm" not in file.read_text(), file
