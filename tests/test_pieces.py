"""Procedures in pieces against serial runs of the whole functions."""

import random

import duckdb
import pyarrow as pa
from pyspark.sql import functions as F

from retro.app import transpile as X
from retro.operators import pieces as Pieces
from retro.operators import replay as R
from retro.operators import values
from retro.plans import whatif as P
from retro.workloads import applications as App

SF = "/root/testdata/sf0.001"
LISTS = {"lines": ["n", "part", "qty"]}


def _functions():
    def transfer(db, cust, other, total):
        """Two customers in one call: their table is one component."""
        if db.read("customer", cust, "balance") >= total:
            db.write("customer", cust, "balance", db.read("customer", cust, "balance") - total)
            db.write("customer", other, "balance", db.read("customer", other, "balance") + total)

    def restock(db, part, qty):
        db.write("stock", part, "quantity", db.read("stock", part, "quantity") + qty)

    return {"new_order": App.new_order, "pay": App.pay, "transfer": transfer, "restock": restock}


def _state(frame):
    return {(r.tbl, r.row_key, r.col): values.decode(r.val) for r in frame.collect()}


def test_pieces_follow_tables_values_and_keys():
    fns = _functions()
    procedure = {n: X.explore(f, lists=LISTS) for n, f in fns.items()}
    own = {p.group: p for p in Pieces.split({"new_order": procedure["new_order"]})["new_order"]}
    assert set(own) == {"orders", "customer", "line", "stock"} and [g for g, p in own.items() if p.fold is None] == ["stock"]
    assert {g: p.rows for g, p in own.items()} == {"orders": None, "customer": None, "line": "lines", "stock": "lines"}
    assert own["stock"].key == (("var", "lines_part"),) and own["line"].key == (("var", "oid"), ("var", "lines_n"))
    # another procedure that ties two rows makes the customers one component, and nothing else
    both = {p.group: p for p in Pieces.split(procedure)["new_order"]}
    assert both["customer"].key is None and both["customer"].fold is None and both["stock"].key is not None and both["line"].fold is not None

    def last_part(db, cust, lines):
        for row in db.each(lines):
            db.write("line", (cust, row["n"]), "qty", row["qty"])
        db.write("customer", cust, "last", row["part"])

    whole = Pieces.split({"last_part": X.explore(last_part, lists=LISTS)})["last_part"]
    assert len(whole) == 1 and whole[0].rows is None and whole[0].key is None


def test_whatif_in_pieces_equals_a_serial_run_of_the_functions(spark):
    fns = _functions()
    rng, kinds = random.Random(3), ["new_order", "new_order", "restock", "pay", "transfer"]
    calls = []
    for i in range(1, 121):
        lines = [(n + 1, rng.randint(0, 3), rng.randint(1, 60)) for n in range(rng.randint(0, 4))]
        calls.append((i, rng.choice(kinds), rng.randint(0, 4), rng.randint(0, 4), 1000 + i, rng.randint(1, 50), rng.randint(0, 3), rng.randint(1, 99), rng.randint(1, 9), lines))
    frame = spark.createDataFrame(calls, "idx long, fn string, cust long, other long, oid long, total long, part long, qty long, amount long, lines array<struct<n:long,part:long,qty:long>>")
    for names in (["new_order"], ["new_order", "restock"], ["new_order", "restock", "pay", "transfer"]):
        gone, own = set(rng.sample(range(1, 121), 20)), [c for c in calls if c[1] in names]
        db = X.Cells()
        for c in own:
            if c[0] not in gone:
                args = dict(zip(frame.columns, c, strict=True)) | {"lines": [dict(zip(LISTS["lines"], x, strict=True)) for x in c[9]]}
                X.to_python(X.explore(fns[c[1]], lists=LISTS))(db, args)
        want = {(t, R.key_text(k), c): v for (t, k, c), v in db.values.items() if c}
        made = P.pieces_whatif(frame.where(F.col("fn").isin(names)), spark.createDataFrame([(g,) for g in gone], "idx long"), {n: X.explore(fns[n], lists=LISTS) for n in names})
        assert _state(made) == want


def test_new_orders_replay_part_by_part(spark, monkeypatch):
    """No component of the replay holds more calls than a part has lines."""
    from retro import workload_queries as Q

    plain, largest = R.in_order, []
    monkeypatch.setattr(R, "in_order", lambda calls, *a, **k: largest.append(calls.groupBy("comp").count().agg(F.max("count")).first()[0]) or plain(calls, *a, **k))
    rows = Q.whatif_neworder(spark, SF).count()
    lines = duckdb.sql(f"SELECT max(n) FROM (SELECT count(*) AS n FROM '{SF}/lineitem.parquet' GROUP BY l_partkey)").fetchall()[0][0]
    assert rows and largest and max(largest) <= lines


def test_entries_of_maps_come_as_pairs_also_from_slices():
    kind = pa.list_(pa.struct([("key", pa.string()), ("value", pa.string())]))
    column = pa.array([[{"key": "a", "value": "1"}], None, [], [{"key": "b", "value": None}, {"key": "c", "value": "3"}]], kind)
    assert list(R._listed(column)) == [[("a", "1")], None, [], [("b", None), ("c", "3")]]
    assert list(R._listed(column.slice(2))) == [[], [("b", None), ("c", "3")]] and list(R._listed(column.slice(1, 1))) == [None]
