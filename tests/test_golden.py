"""The worked example: which statements each retroactive operation affects, and what the tables then hold."""

import pytest

from retro.functions.interpreter import replay
from retro.functions.sqlast import parse
from retro.operators import affected as A
from retro.operators.accesses import accesses, column_sets, pinned, read_only
from retro.sources.tables import ELEMENT, element_rows
from retro.workloads import worked_example as W


def level_of(rows, level):
    if level == "column":
        return [(i, m, t, c, [None] * len(k)) for i, m, t, c, k in rows]
    return [(i, m, t, "*", k) for i, m, t, _, k in rows] if level == "row" else rows


def found(level, target, log=None, catalog=None, combine="edge"):
    rows = element_rows(log or W.log(), catalog or W.catalog())
    if level == "cell" and combine == "set":
        return found("column", target, log, catalog) & found("row", target, log, catalog)
    rows = level_of(rows, level)
    return A.ordered_pass(rows, [(t, c, k, i) for i, m, t, c, k in rows if m == "W" and i == target], {target})


def test_fixpoint_on_dataframes_equals_the_ordered_pass(spark):
    rows = spark.createDataFrame(element_rows(W.log(), W.catalog()), ELEMENT).cache()
    for target, level in ((8, "column"), (5, "cell"), (6, "row")):
        targets = spark.createDataFrame([(target,)], "idx long")
        assert {r.idx for r in A.affected(rows, A.seeds(rows, targets), level, targets).collect()} == found(level, target)


@pytest.mark.parametrize("strict", [True, False])
def test_removing_an_order(strict):
    c = W.catalog(strict)
    assert found("column", 8, catalog=c) >= {11}
    assert found("cell", 8, catalog=c) == {11}
    if not strict:
        assert found("column", 8, catalog=c) == {11}


def test_column_level_is_wider_and_set_lies_between():
    for target in (6, 7, 8, 9):
        column, edge, both = found("column", target), found("cell", target), found("cell", target, combine="set")
        assert edge <= both <= column


def test_removing_a_sign_up_touches_only_its_own_rows():
    log = [x for x in W.log() if x[0] in (6, 9, 12, 13)]
    assert found("cell", 6, log) == {12}


def test_ddl_target_reaches_callers():
    assert found("cell", 5) == {8, 10, 11}


def test_transitive_dependency(spark):
    rows = spark.createDataFrame(element_rows(W.log(), W.catalog()), ELEMENT)
    pairs = {tuple(r) for r in A.closure(A.edges(rows).where("src >= 6")).collect()}
    assert (7, 8) in pairs and (8, 11) in pairs and (7, 11) in pairs
    conflict = {tuple(r) for r in A.edges(rows, "conflict").collect()}
    assert {tuple(r) for r in A.edges(rows).collect()} <= conflict


def test_missing_address_rejects_the_order():
    db = replay(W.catalog(), [x for x in W.log() if x[0] != 7])
    assert db.state().get("orders") is None
    assert db.rows("stats")[(1,)]["n_orders"] == 0
    # re-running the logged inserts instead of the application transaction inserts an order without an address
    wrong = [x if x[0] != 8 else (8, parse("INSERT INTO orders (oid, ord_uid) VALUES (1, 'A')"), {}) for x in W.log() if x[0] != 7]
    assert replay(W.catalog(), wrong).rows("stats")[(1,)]["n_orders"] == 1


def test_alias_and_predicates():
    users = W.catalog().table("users")
    where = lambda text: parse(f"DELETE FROM users WHERE {text}").where
    assert pinned(where("nickname = 'bo'"), users) == ((("alias", "nickname", ("lit", "bo")),),)
    assert len(pinned(where("uid = 'A' OR uid IN ('B', 'C')"), users)) == 3
    assert pinned(where("uid = 'A' OR email = 'x'"), users) == ()
    assert pinned(where("uid = 'A' AND email = 'x'"), users) == ((("lit", "A"),),)
    assert pinned(where("email = 'x'"), users) == ()


def test_branches_are_united_and_read_only_is_seen():
    c = W.catalog()
    read, written = column_sets(parse("CALL place(1, 'A')"), c)
    assert "address.owner_uid" in read and "orders.oid" in written and "_S.place" in read
    assert read_only(parse("SELECT nickname FROM users WHERE uid = 'A'"), c)
    assert any(a.table == "users" and a.keys == ((("lit", "A"),),) for a in accesses(parse("CALL place(1, 'A')"), c))


def test_overwritten_level_is_not_a_dependency():
    log = W.membership_log(200)
    assert found("cell", 16, log) == set() or found("cell", 16, log) == {99}
    full = replay(W.catalog(), log)
    without = replay(W.catalog(), [x for x in log if x[0] != 16])
    assert full.state() == without.state()
