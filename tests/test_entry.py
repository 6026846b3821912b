"""Every registered query of the engine against its SQL, and the entry without the optional parts."""

from __future__ import annotations

import subprocess
import sys

import pytest

from hotkeys import queries

SLOW = {"accuracy_by_skew", "error_by_length", "error_by_owners", "inner_costs_by_skew", "qualitative_report", "accuracy_report_words", "inner_agreement_conversations"}


def rows_of(frame):
    ordered = frame[sorted(frame.columns)]
    clean = ordered.astype(object).where(ordered.notna(), None)
    return sorted(repr([round(x, 9) if isinstance(x, float) else x for x in row]) for row in clean.values.tolist())


@pytest.mark.parametrize("name", sorted(set(queries.QUERIES) - SLOW))
def test_query(name, spark, sf, duck):
    found = queries.QUERIES[name](spark, sf).toPandas()
    if name in queries.ORACLES:
        assert rows_of(found) == rows_of(duck.execute(queries.ORACLES[name]).df())
    else:
        assert len(found)


def test_entry_and_shipping(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_import_without_the_training_data_operators():
    code = "import sys; sys.modules['corpus_pipeline'] = None; sys.modules['hotkeys.llm'] = None; import __spark_entry__ as e; print(len(e.queries()), any(k.startswith('op') for k in e.queries()))"
    done = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, timeout=120, cwd=__file__.rsplit("/", 2)[0])
    assert done.stdout.split()[-1] == "False", done.stderr
