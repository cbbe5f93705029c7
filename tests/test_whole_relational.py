"""Relational operators over whole tables against their SQL."""

from treefold.operators.relational import OPS


def test_relational_on_all_rows(spark, sf):
    import duckdb

    con = duckdb.connect()
    for t in ("customer", "supplier", "events"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    for name in ("op_heap_ancestors_all", "op_full_children_all", "op_sort_nulls_all"):
        run, sql = OPS[name]
        got, rel = [tuple(r) for r in run(spark, sf).collect()], con.sql(sql)
        want = [tuple(dict(zip(rel.columns, r))[c] for c in run(spark, sf).columns) for r in rel.fetchall()]
        assert got == want if name == "op_sort_nulls_all" else sorted(map(str, got)) == sorted(map(str, want)), name
