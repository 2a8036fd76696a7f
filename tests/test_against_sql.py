"""Queries against their SQL in DuckDB, at sizes where a rule that follows the rows would give another answer."""

import os

import pytest
from conftest import SF


def differences(spark, name, folder=SF, run=None):
    """Rows of the SQL that the query hasn't, and rows of the query that the SQL hasn't."""
    import duckdb

    import __spark_entry__ as e

    got = (run or e.queries()[name])(spark, folder).toArrow()
    db = duckdb.connect()
    for t in os.listdir(folder):
        db.execute(f"CREATE VIEW {t.split('.')[0]} AS SELECT * FROM read_parquet('{folder}/{t}')")
    db.register("got", got)
    db.execute(f"CREATE TABLE want AS {e.oracle_sql()[name]}")
    cols = ", ".join(c for c, *_ in db.execute("DESCRIBE want").fetchall())
    return tuple(len(db.execute(f"SELECT {cols} FROM {a} EXCEPT ALL SELECT {cols} FROM {b}").fetchall()) for a, b in (("want", "got"), ("got", "want")))


@pytest.mark.parametrize("name", ["W_cell_classes", "W_kdtree_build_charge5", "W_kdtree_build_line5", "W_postorder", "W_kdtree_build_doc5", "m_node_boxes"])
def test_trees_have_the_levels_of_the_sql(spark, name):
    assert differences(spark, name) == (0, 0)


@pytest.mark.parametrize("name", ["op_join_cross_topk", "op_map"])
def test_empty_and_missing_texts(spark, tmp_path, name):
    texts = [(1, "", "en"), (2, "tenne", "en"), (3, None, "fr"), (4, "", "de"), (5, "Nennen", "fr"), (6, "x", None)]
    spark.createDataFrame(texts, "doc_id long, text string, lang string").coalesce(1).write.parquet(f"{tmp_path}/d")
    folder = tmp_path / "in"
    folder.mkdir()
    next((tmp_path / "d").glob("*.parquet")).rename(folder / "documents.parquet")
    assert differences(spark, name, str(folder)) == (0, 0)


def test_recursion_over_many_rows(spark, tmp_path):
    """130,000 cells have over a million rows of paths."""
    folder = tmp_path / "in"
    folder.mkdir()
    spark.range(130_000).selectExpr("id AS c_custkey").coalesce(1).write.parquet(f"{tmp_path}/c")
    next((tmp_path / "c").glob("*.parquet")).rename(folder / "customer.parquet")
    assert differences(spark, "op_recursive", str(folder)) == (0, 0)


@pytest.mark.parametrize("name", ["W_selectivity_sweep", "m_choose_plan", "W_hull_similar", "m_poly_strict", "m_selectivity_counts"])
def test_queries_over_many_leaves(spark, name, monkeypatch):
    """Covers of hundreds of intervals, as trees of some million rows have them."""
    import __spark_entry__ as e
    from cellspace.operators import kdtree
    from cellspace.workloads import base

    monkeypatch.setattr(kdtree, "leaf_levels", lambda rows: 12)
    monkeypatch.setattr(base, "_KEPT", {})
    if name in e.oracle_sql():
        assert differences(spark, name) == (0, 0)
    else:
        assert e.queries()[name](spark, SF).count() == {"W_selectivity_sweep": 27, "m_choose_plan": 8}[name]
