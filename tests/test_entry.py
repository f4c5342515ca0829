"""Every query with SQL gives the same rows as that SQL at the smallest scale; the others give rows."""

import pytest

import __spark_entry__ as entry

SQL, ALL = entry.oracle_sql(), entry.queries()
#: Whole experiments take minutes; bench and the driver run them.
SLOW = {n for n in ALL if n.startswith(("x", "i2", "c4", "c5", "op1_", "op2_", "op4_", "op5_", "op8_", "op9_", "op10_", "pipeline"))} - set(SQL)


def rows(frame):
    def plain(v):
        if v is None or str(v) in ("NaT", "<NA>", "nan"):
            return "-"
        if isinstance(v, float):
            return f"{v:.5g}"
        return str(v.tolist() if hasattr(v, "tolist") else v)

    cols = sorted(frame.columns)
    return cols, sorted(tuple(plain(v) for v in r) for r in frame[cols].astype(object).itertuples(index=False))


@pytest.mark.parametrize("name", sorted(SQL))
def test_same_as_sql(spark, duck, sf, name):
    assert rows(ALL[name](spark, sf).toPandas()) == rows(duck.execute(SQL[name]).df())


@pytest.mark.parametrize("name", sorted(set(ALL) - set(SQL) - SLOW))
def test_gives_rows(spark, sf, name):
    assert ALL[name](spark, sf).columns


def test_entry(spark):
    assert entry.entry(spark).count() > 0
