"""Registered queries of the remaining workloads, levels of analysis and measures, with the SQL that must give the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from retro import queries as Q
from retro.app.transpile import explore
from retro.catalog import Catalog, Table
from retro.functions.sqlast import parse
from retro.operators import affected as A
from retro.operators import hashing as H
from retro.operators import replay as R
from retro.operators import values
from retro.operators import versions as V
from retro.plans import whatif as P
from retro.sources.tables import checkpointed, dense_index, elements, table
from retro.workloads import applications as App
from retro.workloads import histories as W

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}


def query(sql: str | None = None):
    def keep(fn):
        QUERIES[fn.__name__] = fn
        if sql:
            ORACLE[fn.__name__] = sql
        return fn

    return keep


def _replayer(functions: dict[str, Callable], lists: dict | None = None):
    return R.replayer(R.Body(functions, {name: explore(f, lists=lists) for name, f in functions.items()}))


def _cells(state: DataFrame, tbl: str, columns: dict[str, str]) -> DataFrame:
    """One row for each row of a table of typed cells: (row_key, columns as their SQL types)."""
    own = state.where(F.col("tbl") == tbl)
    return own.groupBy("row_key").agg(*[values.plain(F.max(F.when(F.col("col") == c, F.col("val"))), of).alias(c) for c, of in columns.items()])


def _whatif(rows: DataFrame, targets: DataFrame, replay, initial: DataFrame | None = None) -> DataFrame:
    """The state after the operation: the log's versions, then what the engine makes of them."""
    return V.as_of(P.component_whatif(rows, targets, checkpointed(replay(rows, initial)), replay, initial=initial))


# ---- levels of analysis -------------------------------------------------------------------------------------------------

_PROFILE = {
    "click": "UPDATE profile SET location = :cents WHERE user_id = :user_id",
    "purchase": "UPDATE profile SET balance = balance + :cents WHERE user_id = :user_id",
    "view": "SELECT balance FROM profile WHERE user_id = :user_id",
    "signup": "INSERT INTO audit (event_id, place) SELECT :event_id, location FROM profile WHERE user_id = :user_id",
    "error": "CALL compare(:event_id, :other, :user_id)",
}


def _profile(spark, sf):
    """Elements of the events as statements on profiles, and the first click at a tenth of the history. An error reads two profiles: the location of the
    next user and the status of its own."""
    catalog = Catalog(strict_keys=False).add(Table("profile", ("user_id", "balance", "location", "status"), ("user_id",)), Table("audit", ("event_id", "place"), ("event_id",)))
    catalog.procedures["compare"] = parse("""CREATE PROCEDURE compare(event_id, other, user_id) BEGIN
      SELECT location INTO :place FROM profile WHERE user_id = :other;
      SELECT status INTO :mark FROM profile WHERE user_id = :user_id;
      INSERT INTO audit (event_id, place) VALUES (:event_id, :place); END""")
    calls = checkpointed(W.event_calls(spark, sf).withColumn("other", F.col("user_id") + 1))
    rows = checkpointed(elements(W.as_history(calls, "event_type", ["user_id", "other", "cents", "event_id"]), {k: parse(v) for k, v in _PROFILE.items()}, catalog))
    at = calls.where((F.col("event_type") == "click") & (F.col("commit_idx") >= calls.count() // 10)).agg(F.min("commit_idx")).first()[0]
    target = spark.createDataFrame([(at,)], "idx long")
    return rows, A.seeds(rows, target), target


_CLICK = f"WITH {Q.EV}, t AS (SELECT idx, user_id FROM ev WHERE idx = (SELECT min(idx) FROM ev WHERE event_type = 'click' AND idx >= (SELECT count(*) // 10 FROM ev))) SELECT ev.idx AS commit_idx FROM ev, t WHERE ev.idx > t.idx AND"


@query(f"{_CLICK} event_type IN ('signup', 'error')")
def col_affected_profile(spark, sf):
    rows, seed, target = _profile(spark, sf)
    return A.affected(rows, seed, "column", target).select(F.col("idx").alias("commit_idx"))


@query(f"{_CLICK} (ev.user_id = t.user_id OR event_type = 'error' AND ev.user_id + 1 = t.user_id)")
def row_affected_profile(spark, sf):
    rows, seed, target = _profile(spark, sf)
    return A.affected(rows, seed, "row", target).select(F.col("idx").alias("commit_idx"))


@query(f"{_CLICK} (event_type = 'signup' AND ev.user_id = t.user_id OR event_type = 'error' AND ev.user_id + 1 = t.user_id OR event_type = 'error' AND ev.user_id = t.user_id)")
def cell_set_affected_profile(spark, sf):
    """Statements in both closures: those that read the column of one user and the row of another are among them."""
    rows, seed, target = _profile(spark, sf)
    return A.cell_affected(rows, seed, target, "set").select(F.col("idx").alias("commit_idx"))


_KINDS = "(SELECT idx, cust, oid, CASE fn WHEN 'order' THEN 'order' ELSE fn END AS fn FROM shop WHERE cust < 12 AND fn <> 'record')"


def _shop_edges(spark, sf, kind, level):
    calls, rows = Q._shop(spark, sf)
    few = calls.where("cust < 12 and fn <> 'record'").select(F.col("commit_idx").alias("idx"))
    return A.edges(rows.join(F.broadcast(few), "idx", "left_semi"), kind, level)


#: Which statement kinds read a column that which others wrote: addresses and orders read users, orders read addresses.
_READS = "(VALUES ('signup', 'address'), ('signup', 'order'), ('address', 'order'), ('signup', 'signup'), ('address', 'address'), ('order', 'order'))"


@query(f"WITH {Q.SHOP}, a AS {_KINDS} SELECT w.idx AS src, r.idx AS dst FROM a w JOIN a r ON w.idx < r.idx JOIN {_READS} d(x, y) ON w.fn = x AND r.fn = y")
def col_edges_shop(spark, sf):
    """The pair rule by columns among the statements of twelve customers: a later statement reads a column that an earlier one wrote (an insert reads its table's key)."""
    return _shop_edges(spark, sf, "dependency", "column")


@query(f"WITH {Q.SHOP}, a AS {_KINDS} SELECT w.idx AS src, r.idx AS dst FROM a w JOIN a r ON w.idx < r.idx JOIN {_READS} d(x, y) ON w.fn = x AND r.fn = y WHERE w.cust = r.cust")
def cell_edges_shop(spark, sf):
    """The same cell by cell: only statements about one customer, which identifies the rows of orders too."""
    return _shop_edges(spark, sf, "dependency", "cell")


@query(f"WITH {Q.SHOP}, a AS {_KINDS}, d(x, y) AS (SELECT x, y FROM {_READS} v(x, y) UNION SELECT y, x FROM {_READS} v(x, y)) SELECT w.idx AS src, r.idx AS dst FROM a w JOIN a r ON w.idx < r.idx JOIN d ON w.fn = x AND r.fn = y")
def conflict_edges_shop(spark, sf):
    """The compared definition by columns: also a write after a read and a write after a write."""
    return _shop_edges(spark, sf, "conflict", "column")


# ---- workloads ------------------------------------------------------------------------------------------------------------


@query(f"""WITH {Q.EV}, e2 AS (SELECT * FROM ev WHERE idx % 100 <> 0), u AS (SELECT DISTINCT user_id FROM ev)
SELECT CAST(u.user_id AS VARCHAR) AS row_key, arg_max(cents, idx) FILTER (WHERE event_type = 'click') AS location, arg_max(k, idx) FILTER (WHERE event_type = 'purchase') AS bits, arg_max('k=' || k, idx) FILTER (WHERE event_type = 'purchase') AS label
FROM u LEFT JOIN e2 ON e2.user_id = u.user_id WHERE u.user_id % 5 <> 0 GROUP BY u.user_id""")
def whatif_subscriber_updates(spark, sf):
    """Locations and data of subscribers (four users of five), with texts; every hundredth statement removed."""
    e = W.event_calls(spark, sf).withColumn("label", F.concat(F.lit("k="), "k"))
    users = e.select("user_id").distinct()
    e = e.where("event_type in ('click', 'purchase')").withColumnsRenamed({"user_id": "user", "cents": "place", "k": "bits"})
    args = F.when(F.col("event_type") == "click", values.arguments(e, "user", "place")).otherwise(values.arguments(e, "user", "bits", "label"))
    rows = checkpointed(e.select(F.col("commit_idx").alias("idx"), F.col("user").alias("comp"), F.when(F.col("event_type") == "click", "update_location").otherwise("update_data").alias("fn"), args.alias("args")))
    known = users.where("user_id % 5 <> 0").select(F.col("user_id").alias("comp"), F.lit("subscriber").alias("tbl"), F.col("user_id").cast("string").alias("row_key"), F.lit("active").alias("col"), F.lit("btrue").alias("val"))
    replay = _replayer({"update_location": App.update_location, "update_data": App.update_data})
    versions = P.component_whatif(rows, rows.where("idx % 100 = 0").select("idx"), checkpointed(replay(rows, known)), replay, initial=known)
    state = V.replayed(known, versions)
    return _cells(state, "subscriber", {"location": "long", "bits": "long", "label": "string"})


@query(f"""WITH {Q._LINES}, e AS (SELECT *, 'c' || cust || '-' || idx AS name, 't' || part || '|' || idx AS title FROM li WHERE o_orderkey % 100 <> 0)
SELECT 'customer' AS tbl, CAST(cust AS VARCHAR) AS row_key, arg_max(name, idx) AS val FROM e WHERE idx % 50 = 0 GROUP BY cust
UNION ALL SELECT 'part', CAST(part AS VARCHAR), arg_max(title, idx) FROM e WHERE idx % 70 = 0 AND idx % 50 <> 0 GROUP BY part""")
def whatif_reviews_renames(spark, sf):
    """Every 50th line renames its customer, every 70th retitles its part; the lines of every hundredth order removed. The values are texts."""
    calls = Q._ratings(spark, sf).where("commit_idx % 50 = 0 or commit_idx % 70 = 0").withColumns({"name": F.concat(F.lit("c"), "cust", F.lit("-"), "commit_idx"), "title": F.concat(F.lit("t"), "part", F.lit("|"), "commit_idx")})
    rename = F.col("commit_idx") % 50 == 0
    args = F.when(rename, values.arguments(calls, "cust", "name")).otherwise(values.arguments(calls, "part", "title"))
    comp = F.when(rename, 2 * F.col("cust")).otherwise(2 * F.col("part") + 1).cast("long")
    rows = checkpointed(calls.select(F.col("commit_idx").alias("idx"), comp.alias("comp"), F.when(rename, "rename_customer").otherwise("retitle_part").alias("fn"), args.alias("args"), "o_orderkey"))
    targets = rows.where("o_orderkey % 100 = 0").select("idx")
    state = _whatif(rows.drop("o_orderkey"), targets, _replayer({"rename_customer": App.rename_customer, "retitle_part": App.retitle_part}))
    return state.select("tbl", "row_key", values.plain(F.col("val"), "string").alias("val"))


def _order_calls(spark, sf):
    """(idx, fn, cust, oid, total, lines): each order with its lines as a list."""
    lines = Q._ratings(spark, sf).select("o_orderkey", "commit_idx", F.col("part").cast("long").alias("part"), F.floor(F.col("qty") / 100).cast("long").alias("qty"))
    first = F.min("commit_idx").alias("first")
    packed = F.transform(F.array_sort(F.collect_list(F.struct("commit_idx", "part", "qty"))), lambda x, i: F.struct((i + 1).alias("n"), x["part"].alias("part"), x["qty"].alias("qty")))
    lines = lines.groupBy("o_orderkey").agg(packed.alias("lines"), first).drop("first")
    o = W.order_calls(spark, sf).join(lines, "o_orderkey", "left").withColumn("lines", F.coalesce("lines", F.array().cast(lines.schema["lines"].dataType)))
    o = o.withColumnsRenamed({"o_custkey": "cust", "o_orderkey": "oid"})
    return o.select(F.col("commit_idx").alias("idx"), F.lit("new_order").alias("fn"), "cust", "oid", "total", "lines")


@query(f"""WITH RECURSIVE {Q._LINES}, {Q.ORD}, g AS (SELECT part, qty // 100 AS q, row_number() OVER (PARTITION BY part ORDER BY idx) AS n FROM li WHERE o_orderkey % 100 <> 7),
r AS (SELECT part, 0::BIGINT AS n, 0::BIGINT AS s, 0::BIGINT AS f FROM (SELECT DISTINCT part FROM g) UNION ALL SELECT r.part, g.n, CASE WHEN s - q < 10 THEN s - q + 91 ELSE s - q END, f + CASE WHEN s - q < 10 THEN 1 ELSE 0 END FROM r JOIN g ON g.part = r.part AND g.n = r.n + 1)
SELECT 'stock' AS tbl, CAST(part AS VARCHAR) AS row_key, arg_max(s, n) AS amount, arg_max(f, n) AS n FROM r GROUP BY part
UNION ALL SELECT 'customer', CAST(o_custkey AS VARCHAR), -CAST(sum(total) AS BIGINT), NULL FROM od WHERE o_orderkey % 100 <> 7 GROUP BY o_custkey
UNION ALL SELECT 'line', 'all', CAST(sum(qty // 100) AS BIGINT), count(*) FROM li WHERE o_orderkey % 100 <> 7""")
def whatif_neworder(spark, sf):
    """Whole new orders: header, lines in a loop with a refill branch, stock, balance. Orders whose key ends in 07 removed. Stock ties all
    orders together, so they run in pieces: header, balance and lines fold, and each line's stock is a call of its own, replayed part by part."""
    calls = checkpointed(_order_calls(spark, sf))
    state = checkpointed(P.pieces_whatif(calls, calls.where("oid % 100 = 7"), {"new_order": explore(App.new_order, lists={"lines": ["n", "part", "qty"]})}))
    none = F.lit(None).cast("long").alias("n")
    stock = _cells(state, "stock", {"quantity": "long", "refills": "long"}).select(F.lit("stock").alias("tbl"), "row_key", F.col("quantity").alias("amount"), F.coalesce("refills", F.lit(0)).alias("n"))
    customer = _cells(state, "customer", {"balance": "long"}).select(F.lit("customer").alias("tbl"), "row_key", F.col("balance").alias("amount"), none)
    line = _cells(state, "line", {"qty": "long"}).agg(F.sum("qty").alias("amount"), F.count("*").alias("n")).select(F.lit("line").alias("tbl"), F.lit("all").alias("row_key"), "amount", "n")
    return stock.unionByName(customer).unionByName(line)


@query(f"""WITH {Q.EV}, {Q.ORD}, m AS (SELECT o_custkey AS cust, 0 AS pay, total AS cents FROM od WHERE o_orderkey % 100 <> 0 UNION ALL SELECT user_id, 1, cents FROM ev WHERE event_type = 'purchase' AND event_id % 50 <> 0)
SELECT CAST(cust AS VARCHAR) AS row_key, CAST(sum(CASE pay WHEN 1 THEN cents ELSE -cents END) AS BIGINT) AS balance, CAST(sum(cents) FILTER (WHERE pay = 1) AS BIGINT) AS paid, CAST(count(*) FILTER (WHERE pay = 1) AS BIGINT) AS payments FROM m GROUP BY cust""")
def whatif_payments(spark, sf):
    """Orders charge and purchases pay, in decimals; every hundredth order and every fiftieth payment removed."""
    money = lambda c: (F.col(c).cast("decimal(18,2)") / 100).cast("decimal(18,2)").alias("amount")
    o = W.order_calls(spark, sf).select(F.col("o_orderdate").cast("timestamp").alias("ts"), F.lit("charge").alias("fn"), F.col("o_orderkey").alias("id"), F.col("o_custkey").alias("cust"), money("total"), (F.col("o_orderkey") % 100 == 0).alias("gone"))
    e = W.event_calls(spark, sf).where("event_type = 'purchase'").select("ts", F.lit("pay").alias("fn"), F.col("event_id").alias("id"), F.col("user_id").alias("cust"), money("cents"), (F.col("event_id") % 50 == 0).alias("gone"))
    calls = dense_index(o.unionByName(e), "ts", "fn", "id", name="idx")
    rows = checkpointed(calls.select("idx", F.col("cust").alias("comp"), "fn", values.arguments(calls, "cust", "amount").alias("args"), "gone"))
    state = _whatif(rows.drop("gone"), rows.where("gone").select("idx"), _replayer({"charge": App.charge, "pay": App.pay}))
    wide = _cells(state, "customer", {"balance": "decimal(28,2)", "paid": "decimal(28,2)", "payments": "long"})
    cents = lambda c: (F.col(c) * 100).cast("long").alias(c)
    return wide.select("row_key", cents("balance"), cents("paid"), F.coalesce("payments", F.lit(0)).alias("payments"))


@query("""WITH s AS (SELECT l_orderkey AS oid, max(l_shipdate) AS at FROM lineitem GROUP BY l_orderkey)
SELECT CAST(o_orderkey AS VARCHAR) AS row_key, s.at IS NOT NULL AS delivered, epoch_us(s.at) AS micros FROM orders LEFT JOIN s ON s.oid = o_orderkey WHERE o_orderkey % 100 <> 0""")
def whatif_delivery(spark, sf):
    """Orders are entered, then delivered at the ship date of their last line; every hundredth entry removed, so its delivery finds no order."""
    o = table(spark, sf, "orders").select(F.lit(0).alias("phase"), F.col("o_orderkey").alias("oid"), F.col("o_custkey").alias("cust"), F.lit(None).cast("timestamp").alias("at"))
    li = table(spark, sf, "lineitem").groupBy(F.col("l_orderkey").alias("oid")).agg(F.max(F.col("l_shipdate").cast("timestamp")).alias("at")).select(F.lit(1).alias("phase"), "oid", F.lit(None).cast("long").alias("cust"), "at")
    calls = dense_index(o.unionByName(li), "phase", "oid", name="idx")
    args = F.when(F.col("phase") == 0, values.arguments(calls, "oid", "cust")).otherwise(values.arguments(calls, "oid", "at"))
    rows = checkpointed(calls.select("idx", F.col("oid").alias("comp"), F.when(F.col("phase") == 0, "enter_order").otherwise("deliver").alias("fn"), args.alias("args"), "phase"))
    targets = rows.where("phase = 0 and comp % 100 = 0").select("idx")
    state = _whatif(rows.drop("phase"), targets, _replayer({"enter_order": App.enter_order, "deliver": App.deliver}))
    return _cells(state, "orders", {"delivered": "boolean", "at": "timestamp"}).select("row_key", "delivered", F.unix_micros("at").alias("micros"))


_ITEMS = 5
_CART = {"click": "cart_add", "error": "cart_remove", "purchase": "cart_checkout", "signup": "give_coupon"}


@query(f"""WITH RECURSIVE {Q.EV}, x AS (SELECT idx, user_id, event_type, k % {_ITEMS} AS item FROM ev WHERE event_type IN ('click', 'error') AND idx % 100 <> 0 UNION ALL SELECT idx, user_id, event_type, i.item FROM ev, (SELECT unnest(range({_ITEMS})) AS item) i WHERE event_type = 'purchase' AND idx % 100 <> 0),
g AS (SELECT *, row_number() OVER (PARTITION BY user_id, item ORDER BY idx) AS n FROM x),
r AS (SELECT user_id, item, 0::BIGINT AS n, 0::BIGINT AS qty, 0::BIGINT AS sold FROM (SELECT DISTINCT user_id, item FROM g)
 UNION ALL SELECT r.user_id, r.item, g.n, CASE event_type WHEN 'click' THEN qty + 1 WHEN 'error' THEN greatest(qty - 1, 0) ELSE 0 END, sold + CASE WHEN event_type = 'purchase' THEN qty ELSE 0 END FROM r JOIN g ON g.user_id = r.user_id AND g.item = r.item AND g.n = r.n + 1),
s AS (SELECT user_id, item, arg_max(sold, n) AS sold FROM r GROUP BY ALL), c AS (SELECT user_id, arg_max(k, idx) AS percent FROM ev WHERE event_type = 'signup' AND idx % 100 <> 0 GROUP BY user_id)
SELECT CAST(u.user_id AS VARCHAR) AS row_key, CAST(coalesce((SELECT sum(sold) FROM s WHERE s.user_id = u.user_id), 0) AS BIGINT) AS sold, percent FROM (SELECT DISTINCT user_id FROM ev WHERE event_type <> 'view') u LEFT JOIN c ON c.user_id = u.user_id""")
def whatif_webshop(spark, sf):
    """Carts with checkouts that loop over items, and coupons whose drawn value was recorded; every hundredth statement removed."""
    e = W.event_calls(spark, sf).where("event_type <> 'view'").withColumn("item", F.col("k") % _ITEMS).withColumnRenamed("user_id", "user")
    e = e.withColumn("items", F.transform(F.sequence(F.lit(0), F.lit(_ITEMS - 1)), lambda i: F.struct(i.alias("item"))))
    kind = F.col("event_type")
    args = F.when(kind == "purchase", values.arguments(e, "user", "items")).when(kind == "signup", values.arguments(e, "user")).otherwise(values.arguments(e, "user", "item"))
    fn = F.lit(None).cast("string")
    for k, name in _CART.items():
        fn = F.when(kind == k, name).otherwise(fn)
    drawn = F.create_map(F.lit("draw"), values.encoded(F.col("k"), e.schema["k"].dataType))
    rows = checkpointed(e.select(F.col("commit_idx").alias("idx"), F.col("user").alias("comp"), fn.alias("fn"), args.alias("args"), drawn.alias("recorded")))
    replay = _replayer({name: getattr(App, name) for name in _CART.values()}, {"items": ["item"]})
    state = checkpointed(_whatif(rows, rows.where("idx % 100 = 0").select("idx"), replay))
    sold = state.where("tbl = 'sold'").groupBy(F.substring_index("row_key", "|", 1).alias("row_key")).agg(F.sum(values.plain(F.col("val"), "long")).alias("sold"))
    users = rows.select(F.col("comp").cast("string").alias("row_key")).distinct()
    return users.join(sold, "row_key", "left").join(_cells(state, "coupon", {"percent": "long"}), "row_key", "left").select("row_key", F.coalesce("sold", F.lit(0)).alias("sold"), "percent")


# ---- early stop ------------------------------------------------------------------------------------------------------------


def set_level(db, user, level):
    db.write("membership", user, "level", level)


def _levels(spark, sf):
    e = W.event_calls(spark, sf).where("event_type <> 'view'")
    args = F.create_map(F.lit("user"), F.col("user_id"), F.lit("level"), W.band(F.col("cents")))
    return checkpointed(e.select(F.col("commit_idx").alias("idx"), F.col("user_id").alias("comp"), F.lit("set_level").alias("fn"), args.alias("args")))


@query(f"WITH {Q.EV}, l AS (SELECT user_id, idx, row_number() OVER (PARTITION BY user_id ORDER BY idx) AS n FROM ev WHERE event_type <> 'view') SELECT user_id, idx AS stop_idx FROM l WHERE n = 2")
def early_stop_index(spark, sf):
    """REMOVE every user's first level: replay of a user's calls stops at the next assignment, where the hash of the table is as it was."""
    calls = _levels(spark, sf)
    targets = calls.groupBy("comp").agg(F.min("idx").alias("idx")).select("idx")
    logged = checkpointed(_replayer({"set_level": set_level})(calls))
    marks = calls.join(targets, "idx", "left_semi").select("comp", F.col("idx").alias("first"), F.col("idx").alias("last"))
    again = calls.join(marks.select("comp", "first"), "comp").where("idx > first").drop("first")
    old = logged.join(marks, "comp").where("idx >= first").drop("first")
    made = R.in_order(again, None, R.Body({"set_level": set_level}, {"set_level": explore(set_level)}), logged=old, literal=True)
    return made.where(F.col("tbl") == R.STOPPED).select(F.col("comp").alias("user_id"), F.col("idx").alias("stop_idx"))


@query(f"WITH {Q.EV} SELECT 'membership' AS tbl, CAST(user_id AS VARCHAR) AS row_key, 'level' AS col, arg_max(CAST({Q._BAND} AS BIGINT), idx) AS val FROM ev WHERE event_type <> 'view' AND idx <> (SELECT min(idx) FROM ev WHERE event_type <> 'view') GROUP BY user_id")
def whatif_one_component_early_stop(spark, sf):
    """REMOVE the first level of all, with the whole history as one component: buckets run in commit order, and a job beside the next bucket finds the match."""
    calls = checkpointed(_levels(spark, sf).withColumn("comp", F.lit(0).cast("long")))
    replay = _replayer({"set_level": set_level})
    logged = checkpointed(replay(calls))
    ends = calls.agg(F.min("idx"), F.max("idx")).first()
    target = calls.where(F.col("idx") == ends[0]).select("idx")
    step = max(1, (ends[1] - ends[0]) // 10)
    made, _ = P.bucketed_whatif(calls, target, logged, replay, list(range(ends[0] + step, ends[1], step)), literal=True)
    return V.as_of(made)


# ---- rules over states -------------------------------------------------------------------------------------------------------


@query(f"WITH {Q.EV}, f AS (SELECT user_id, min(idx) AS since FROM ev WHERE event_type = 'error' GROUP BY user_id) SELECT ev.user_id, count(*) AS kept FROM ev LEFT JOIN f ON f.user_id = ev.user_id WHERE event_type = 'purchase' AND (since IS NULL OR idx < since) GROUP BY ev.user_id")
def human_rule_state(spark, sf):
    """A rule over the state just before each call: who has the error status makes no more purchases."""
    calls = W.event_calls(spark, sf)
    versions = V.fold(W.balance_effects(calls))
    bought = calls.where("event_type = 'purchase'").withColumn("row_key", F.col("user_id").cast("string"))
    return P.with_state_rules(bought, versions, "accounts", "status", F.col("held") == 1).groupBy("user_id").agg(F.count("*").alias("kept"))


# ---- consulted tables -----------------------------------------------------------------------------------------------------------


@query("""SELECT r_name, count(*) AS customers, CAST(sum(CASE WHEN n_nationkey % 2 = 0 THEN CAST(round(c_acctbal * 100) AS BIGINT) + 100 ELSE CAST(round(c_acctbal * 100) AS BIGINT) END) AS BIGINT) AS cents
FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name""")
def whatif_consulted_nations(spark, sf):
    """A bonus whose statement consults nation and region, which no statement writes: they are read as they are, never undone or replayed."""
    c = table(spark, sf, "customer").join(table(spark, sf, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(table(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    base = c.select(F.col("c_custkey").alias("id"), F.col("n_nationkey").cast("long").alias("nation"), W.cents("c_acctbal").alias("bal"), "r_name")
    bonus = Q.B.Change("update", lambda x: x["nation"] % 2 == 0, {"bal": lambda x: x["bal"] + 100})
    return Q.B.reenact(base, [bonus]).groupBy("r_name").agg(F.count("*").alias("customers"), F.sum("bal").alias("cents"))


@query("SELECT 'benchmark' AS tbl, 'irrelevant' AS class UNION ALL SELECT 'documents', 'consulted' UNION ALL SELECT 'labels', 'mutated' UNION ALL SELECT 'published', 'mutated' UNION ALL SELECT '_S', 'consulted'")
def table_classes_moderation(spark, sf):
    """Classes of the moderation history's tables when the first label is removed: benchmark is read by statements that nothing affects."""
    catalog = Catalog().add(Table("documents", ("doc_id", "source"), ("doc_id",)), Table("labels", ("doc_id", "toxic"), ("doc_id",)), Table("published", ("doc_id", "n"), ("doc_id",)), Table("benchmark", ("item_id", "text"), ("item_id",)))
    templates = {
        "insert": parse("SELECT text FROM benchmark WHERE item_id = 1"),
        "label": parse("INSERT INTO labels (doc_id, toxic) VALUES (:doc_id, :toxic)"),
        "relabel": parse("UPDATE labels SET toxic = toxic + 1 WHERE doc_id = :doc_id"),
        "publish": parse("CALL publish(:doc_id)"),
    }
    catalog.procedures["publish"] = parse("""CREATE PROCEDURE publish(doc_id) BEGIN
      SELECT COUNT(*) INTO :n FROM documents WHERE doc_id = :doc_id;
      SELECT toxic INTO :bad FROM labels WHERE doc_id = :doc_id;
      IF :n > 0 THEN INSERT INTO published (doc_id, n) VALUES (:doc_id, :bad); END IF; END""")
    docs = W.moderation_calls(spark, sf).where("fn = 'label'").select("doc_id", "toxic")
    steps = docs.select("doc_id", "toxic", F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.lit(t).alias("fn")) for k, t in enumerate(("insert", "label", "relabel", "publish"))])).alias("s")).select("doc_id", "toxic", "s.k", "s.fn")
    calls = dense_index(steps, "doc_id", "k")
    rows = checkpointed(elements(W.as_history(calls, "fn", ["doc_id", "toxic"]), templates, catalog))
    target = checkpointed(calls.where("fn = 'label'").agg(F.min("commit_idx").alias("idx")))
    hit = A.affected(rows, A.seeds(rows, target), "cell", target)
    return V.classify_tables(rows, hit).select("tbl", "class")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLE)
