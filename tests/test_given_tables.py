"""Queries that made their data up read a given table."""

import pytest

import __spark_entry__ as entry

NAMES = ["break_even", "cell_pass_table", "daily_cost_curve", "fan_in_report", *[f"dispatch_tree_{s}" for s in ("10_1", "1_3", "4_2", "4_3", "4_4", "5_3", "6_3")]]


@pytest.mark.parametrize("name", NAMES)
def test_reads_orders_and_agrees_with_its_sql(spark, sf_dir, name):
    import duckdb

    found = entry.queries()[name](spark, sf_dir)
    assert any(f.endswith("orders.parquet") for f in found.inputFiles())
    with duckdb.connect() as c:
        c.execute(f"CREATE VIEW orders AS SELECT * FROM read_parquet('{sf_dir}/orders.parquet')")
        want = c.execute(entry.oracle_sql()[name])
        names = [x[0] for x in want.description]
        rows = want.fetchall()
    assert sorted(names) == sorted(found.columns)
    assert sorted(map(repr, rows)) == sorted(repr(tuple(r)) for r in found.select(*names).collect())


def test_text_vectors_take_their_length_once(spark):
    from packvec.functions.vectors import text_vectors

    df = spark.createDataFrame([(1, "a b a"), (2, "A, b. b!"), (3, " ,. "), (4, None)], "id int, text string")
    found = text_vectors(df, "id", "text", 8, "e")
    assert "aggregate(" not in found._jdf.queryExecution().toString()
    got = {r["id"]: r["e"] for r in found.collect()}
    assert sorted(got) == [1, 2] and all(abs(sum(x * x for x in e) - 1) < 1e-12 for e in got.values())


def test_lines_are_numbered_range_by_range(spark, sf_dir):
    import duckdb

    from packvec.sources import tables

    line = tables.load(spark, sf_dir, "lineitem")
    by = sorted(line.columns)
    found = tables.numbered(line, "n", *by)
    assert "row_number" not in found._jdf.queryExecution().toString()  # the only window is over the ranges' sizes
    with duckdb.connect() as c:
        want = c.execute(f"SELECT {', '.join(by)} FROM read_parquet('{sf_dir}/lineitem.parquet') ORDER BY {', '.join(by)}").fetchall()
    got = found.orderBy("n").select("n", *by).collect()
    assert [r["n"] for r in got] == list(range(len(want))) and [tuple(r)[1:] for r in got] == want
    assert tables.numbered(line.where("false"), "n", *by).count() == 0
    lines = tables.lineitem_vl(spark, sf_dir)
    assert lines.schema["vec_id"].dataType.simpleString() == "bigint" and lines.count() == len(want)


@pytest.mark.parametrize("name", ["cache_duplication_sweep", "cache_ratio"])
def test_searches_of_a_sweep_read_the_joined_rows_again(spark, sf_dir, name, monkeypatch):
    from packvec.queries import runs

    plans, real = [], runs.exact.knn
    monkeypatch.setattr(runs.exact, "knn", lambda q, base, k: plans.append(base._jdf.queryExecution().toString()) or real(q, base, k))
    monkeypatch.setattr(runs, "FACTORS", (1, 2))
    found = entry.queries()[name](spark, sf_dir).orderBy("factor").collect()
    assert len(plans) == 2 and not any("Join" in p for p in plans)
    assert [r["factor"] for r in found] == [1, 2] and found[1]["requests"] == 2 * found[0]["requests"]
