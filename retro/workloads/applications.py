"""Further application functions: subscribers, reviews, orders with lines, payments, deliveries, a web shop with a client.

They take a database handle first, like those of `histories`; the transpiler turns them into procedures. Values may be of any type that
`operators.values` knows.
"""

from __future__ import annotations

from html.parser import HTMLParser


# ---- subscribers -----------------------------------------------------------------------------------------------------


def update_location(db, user, place):
    if db.exists("subscriber", user):
        db.write("subscriber", user, "location", place)
    else:
        db.write("errors", user, "n", db.read("errors", user, "n") + 1)


def update_data(db, user, bits, label):
    """Sets the data bits and a text; an unknown subscriber counts an error."""
    if db.exists("subscriber", user):
        db.write("subscriber", user, "bits", bits)
        db.write("subscriber", user, "label", label)
    else:
        db.write("errors", user, "n", db.read("errors", user, "n") + 1)


# ---- reviews -----------------------------------------------------------------------------------------------------------


def rename_customer(db, cust, name):
    db.write("customer", cust, "name", name)


def retitle_part(db, part, title):
    db.write("part", part, "title", title)


# ---- orders ------------------------------------------------------------------------------------------------------------


def new_order(db, cust, oid, total, lines):
    """Header, balance, and for each line its row and the stock, with a refill of 91 when fewer than 10 would be left."""
    db.write("orders", oid, "cust", cust)
    db.write("customer", cust, "balance", db.read("customer", cust, "balance") - total)
    for line in db.each(lines):
        db.write("line", (oid, line["n"]), "qty", line["qty"])
        left = db.read("stock", line["part"], "quantity") - line["qty"]
        if left < 10:
            db.write("stock", line["part"], "quantity", left + 91)
            db.write("stock", line["part"], "refills", db.read("stock", line["part"], "refills") + 1)
        else:
            db.write("stock", line["part"], "quantity", left)


def pay(db, cust, amount):
    db.write("customer", cust, "balance", db.read("customer", cust, "balance") + amount)
    db.write("customer", cust, "paid", db.read("customer", cust, "paid") + amount)
    db.write("customer", cust, "payments", db.read("customer", cust, "payments") + 1)


def charge(db, cust, amount):
    db.write("customer", cust, "balance", db.read("customer", cust, "balance") - amount)


def enter_order(db, oid, cust):
    db.write("orders", oid, "cust", cust)
    db.write("orders", oid, "delivered", False)


def deliver(db, oid, at):
    """Marks an order as delivered at a time, once; an unknown order is an error."""
    if db.exists("orders", oid):
        if not db.read("orders", oid, "delivered"):
            db.write("orders", oid, "delivered", True)
            db.write("orders", oid, "at", at)
    else:
        db.write("errors", 0, "n", db.read("errors", 0, "n") + 1)


# ---- web shop ------------------------------------------------------------------------------------------------------------


def cart_add(db, user, item):
    db.write("cart", (user, item), "qty", db.read("cart", (user, item), "qty") + 1)


def cart_remove(db, user, item):
    qty = db.read("cart", (user, item), "qty")
    if qty > 0:
        db.write("cart", (user, item), "qty", qty - 1)


def cart_checkout(db, user, items):
    """Sells what the cart holds of each item and empties it."""
    for row in db.each(items):
        qty = db.read("cart", (user, row["item"]), "qty")
        if qty > 0:
            db.write("sold", (user, row["item"]), "qty", db.read("sold", (user, row["item"]), "qty") + qty)
            db.write("cart", (user, row["item"]), "qty", 0)


def give_coupon(db, user):
    """A discount that a service outside the database draws."""
    db.write("coupon", user, "percent", db.native("draw", user))


class _Fields(HTMLParser):
    def __init__(self):
        super().__init__()
        self.names: list[str] = []

    def handle_starttag(self, tag, attrs):
        name = dict(attrs).get("name")
        if tag in ("input", "select", "textarea") and name and name not in self.names:
            self.names.append(name)


def form_fields(html: str) -> list[str]:
    """Names of a page's form inputs, which become a client function's symbols."""
    parser = _Fields()
    parser.feed(html)
    return parser.names


def add_clicked(user, item, amount):
    """Client side of the cart: what the browser checks before it sends a request. None: nothing is sent."""
    if amount > 0:
        if item >= 0:
            return (user, item)
    return None


APPLICATION = (update_location, update_data, rename_customer, retitle_part, new_order, pay, charge, enter_order, deliver, cart_add, cart_remove, cart_checkout, give_coupon)
