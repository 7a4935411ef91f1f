"""From application functions to procedures by mixed concrete and symbolic execution.

An application function takes a database handle and arguments, and mixes its own branches with database calls. `explore` runs it with symbol
proxies that carry a concrete value and an expression: operators build expressions, a branch on a symbol records its
condition, database calls are answered by fresh symbols. The untaken side of each branch is solved for and run next, until no side
is left or a limit is reached; sides that were not solved become signals, which delta exploration replaces when they are hit.
The resulting tree is cut to what reaches the database and emitted as SQL script text, as a Python procedure that needs one call, or as Column
expressions. Lists of arguments stay loops.
"""

from __future__ import annotations

import dis
import inspect
import itertools
import time
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F


class Signalled(Exception):
    """A branch that exploration has not seen was reached; carries the code of the signal node."""


# ---- symbols ---------------------------------------------------------------------------------------------------------


class Run:
    """One execution: the decisions to force, and the trace of decisions and database operations."""

    def __init__(self, values: dict, forced: list[bool], limit: int):
        self.values, self.forced, self.trace, self.made, self.limit = values, forced, [], [0], limit

    def value(self, name: str, default=0):
        return self.values.get(name, default)

    def fresh(self, kind: str) -> str:
        """A name that depends on what came before it in its own loop body alone, whatever bodies before it did."""
        self.made[-1] += 1
        return kind + "_".join(map(str, self.made))

    def decide(self, condition, concrete: bool) -> bool:
        self.trace.append(("branch", condition, concrete, _place()))
        if sum(1 for t in self.trace if t[0] == "branch") > self.limit:
            raise OverflowError("too many branches")
        return concrete


def _place() -> tuple:
    f = inspect.currentframe()
    while f and f.f_code.co_filename == __file__:
        f = f.f_back
    return (f.f_code.co_filename, f.f_lineno) if f else ("", 0)


def _expr(x):
    return x.expr if isinstance(x, Symbol) else ("lit", x)


def _value(x):
    return x.concrete if isinstance(x, Symbol) else x


class Symbol:
    """A value with its expression. Arithmetic, comparison and concatenation give symbols; truth records a branch."""

    def __init__(self, run: Run, expr: tuple, concrete):
        self.run, self.expr, self.concrete = run, expr, concrete

    def _with(self, op, other, fn, swapped=False):
        a, b = (other, self) if swapped else (self, other)
        return Symbol(self.run, ("op", op, _expr(a), _expr(b)), fn(_value(a), _value(b)))

    def __bool__(self):
        return self.run.decide(self.expr, bool(self.concrete))

    def __hash__(self):
        return hash(self.expr)

    def __neg__(self):
        return Symbol(self.run, ("op", "neg", self.expr), -self.concrete)


for _name, _op in {"add": "+", "sub": "-", "mul": "*", "mod": "%", "lt": "<", "le": "<=", "gt": ">", "ge": ">=", "eq": "=", "ne": "<>"}.items():

    def _forward(self, other, op=_op):
        if op == "+" and (isinstance(_value(self), str) or isinstance(_value(other), str)):
            return self._with("||", other, lambda a, b: f"{a}{b}")
        return self._with(op, other, _RUN[op])

    def _swapped(self, other, op=_op):
        if op == "+" and isinstance(other, str):
            return self._with("||", other, lambda a, b: f"{a}{b}", True)
        return self._with(op, other, _RUN[op], True)

    setattr(Symbol, f"__{_name}__", _forward)
    if _name in ("add", "sub", "mul", "mod"):
        setattr(Symbol, f"__r{_name}__", _swapped)

_RUN: dict[str, Callable] = {
    "+": lambda a, b: a + b, "-": lambda a, b: a - b, "*": lambda a, b: a * b, "%": lambda a, b: a % b if b else 0, "<": lambda a, b: a < b, "<=": lambda a, b: a <= b, ">": lambda a, b: a > b, ">=": lambda a, b: a >= b,
    "=": lambda a, b: a == b, "<>": lambda a, b: a != b, "||": lambda a, b: f"{a}{b}", "and": lambda a, b: a and b, "or": lambda a, b: a or b,
}


class FakeDb:
    """Answers database calls with symbols; `native` marks a value of a black-box function (clock, random, remote service)."""

    def __init__(self, run: Run):
        self.run = run

    def read(self, table, key, column):
        name = self.run.fresh("db")
        self.run.trace.append(("read", name, table, tuple(map(_expr, _tuple(key))), column))
        return Symbol(self.run, ("var", name), self.run.value(name))

    def exists(self, table, key):
        name = self.run.fresh("db")
        self.run.trace.append(("exists", name, table, tuple(map(_expr, _tuple(key)))))
        return Symbol(self.run, ("var", name), bool(self.run.value(name, False)))

    def write(self, table, key, column, value):
        self.run.trace.append(("write", table, tuple(map(_expr, _tuple(key))), column, _expr(value)))

    def delete(self, table, key):
        self.run.trace.append(("delete", table, tuple(map(_expr, _tuple(key)))))

    def native(self, name, *args):
        symbol = self.run.fresh("native")
        self.run.trace.append(("native", symbol, name, tuple(map(_expr, args))))
        return Symbol(self.run, ("var", symbol), self.run.value(symbol))

    def each(self, rows):
        """The rows of an argument list; one symbolic row stands for all, so a loop stays a loop, with the branches of its body inside."""
        run, outer, body = self.run, self.run.trace, []
        run.made[-1] += 1
        outer.append(("loop", _expr(rows), body))
        run.trace, run.made = body, [*run.made, 0]
        try:
            yield {c: Symbol(run, ("item", c), run.value(f"item.{c}", 1)) for c in rows.concrete}
        finally:
            run.trace, run.made = outer, run.made[:-1]

    def call(self, target, known, *args):
        """A call whose target depends on data: a chain of branches over the known targets; any other target is a signal."""
        for name, fn in known.items():
            if target == name:
                return fn(self, *args)
        self.run.trace.append(("unknown", _expr(target)))
        return None


def _tuple(key):
    return key if isinstance(key, tuple) else (key,)


# ---- solving ---------------------------------------------------------------------------------------------------------


def evaluate(e, env: dict):
    kind = e[0]
    if kind == "lit":
        return e[1]
    if kind == "var":
        return env.get(e[1], 0)
    if kind == "item":
        return env.get(f"item.{e[1]}", 1)
    args = [evaluate(x, env) for x in e[2:]]
    if e[1] == "not":
        return not args[0]
    if e[1] == "neg":
        return -args[0]
    return _RUN[e[1]](*args)


def _names(e) -> set[str]:
    if e[0] in ("var", "item"):
        return {e[1] if e[0] == "var" else f"item.{e[1]}"}
    return set().union(*(_names(x) for x in e[2:])) if e[0] == "op" else set()


def _constants(e) -> set:
    return {e[1]} if e[0] == "lit" else set().union(*(_constants(x) for x in e[2:])) if e[0] == "op" else set()


def solve(path: list[tuple[tuple, bool]], seed: dict, tries: int = 20_000):
    """Values under which every condition has the wanted truth: ("sat", values), ("unsat", None) or ("unknown", None).

    Conditions on one symbol and constants are settled by the boundary values around the constants, which decide them completely;
    several symbols are tried on the product of their boundary values.
    """
    names = sorted(set().union(*(_names(c) for c, _ in path)) if path else set())
    ground = [c for c, _ in path if not _names(c)]
    if any(bool(evaluate(c, {})) != want for c, want in path if c in ground):
        return "unsat", None
    marks = set().union(*(_constants(c) for c, _ in path)) if path else set()
    numbers = sorted({n + d for n in marks | {0, 1} if isinstance(n, int | float) and not isinstance(n, bool) for d in (-1, 0, 1)})
    words = sorted(m for m in marks if isinstance(m, str))
    pool = {}
    for n in names:
        held = seed.get(n)
        used = [c for c, _ in path if n in _names(c)]
        about_words = any(isinstance(k, str) for c in used for k in _constants(c))
        extra = [numbers[-1] * 10 + 7] if numbers else []
        pool[n] = [x for x in ([held] if held is not None else []) + (words + ["?"] if about_words else numbers + extra)]
        if all(c == ("var", n) for c in used):
            pool[n] = [True, False]
    for k, values in enumerate(itertools.product(*pool.values())):
        if k >= tries:
            return "unknown", None
        env = seed | dict(zip(pool, values, strict=True))
        try:
            if all(bool(evaluate(c, env)) == want for c, want in path):
                return "sat", env
        except TypeError:
            continue
    linear = len(names) <= 1 and all(x[0] != "op" or x[1] not in ("*", "%") for c, _ in path for x in [c])
    return ("unsat" if linear else "unknown"), None


# ---- exploration -----------------------------------------------------------------------------------------------------


@dataclass
class Node:
    """steps run in order; then a branch (test, yes, no), or nothing."""

    steps: list[tuple] = field(default_factory=list)
    test: tuple | None = None
    yes: Node | None = None
    no: Node | None = None
    signal: str | None = None

    def loops(self) -> list[Node]:
        return [s[2] for s in self.steps if s[0] == "loop"]

    def paths(self) -> int:
        own = (self.yes.paths() + self.no.paths()) if self.test else int(self.signal is None)
        for body in self.loops():
            own *= body.paths()
        return own

    def signals(self) -> int:
        own = (self.yes.signals() + self.no.signals()) if self.test else int(self.signal is not None)
        return own + sum(body.signals() for body in self.loops())


@dataclass
class Procedure:
    name: str
    params: tuple[str, ...]
    tree: Node
    runs: int = 0
    seconds: float = 0.0


def _merge(node: Node, trace: list[tuple], code: str) -> None:
    steps = []
    for k, t in enumerate(trace):
        if t[0] == "branch":
            node.steps, node.signal = steps, None
            if node.test is None:
                node.test, node.yes, node.no = t[1], Node(signal=f"{code}-{k}y"), Node(signal=f"{code}-{k}n")
            _merge(node.yes if t[2] else node.no, trace[k + 1 :], code)
            return
        if t[0] == "loop":
            same = len(node.steps) > len(steps) and node.steps[len(steps)][0] == "loop"
            body = node.steps[len(steps)][2] if same else Node(signal=f"{code}-{k}l")
            _merge(body, t[2], f"{code}-{k}")
            t = ("loop", t[1], body)
        if t[0] == "unknown":
            node.steps, node.signal = steps, f"{code}-{k}u"
            return
        steps.append(t)
    node.steps, node.signal = steps, None


def _decisions(trace: list[tuple]) -> list[tuple]:
    """(condition, side) of every branch in order, those of loop bodies where the loop stands."""
    out = []
    for t in trace:
        if t[0] == "branch":
            out.append((t[1], t[2]))
        elif t[0] == "loop":
            out += _decisions(t[2])
    return out


def run_once(fn: Callable, values: dict, lists: dict, limit: int = 200) -> list[tuple]:
    run = Run(values, [], limit)
    args = []
    for p in list(inspect.signature(fn).parameters)[1:]:
        args.append(Symbol(run, ("var", p), lists[p] if p in lists else values.get(p, 0)))
    fn(FakeDb(run), *args)
    return run.trace


def explore(fn: Callable, seed: dict | None = None, lists: dict | None = None, max_paths: int = 256, timeout_s: float = 10.0, into: Procedure | None = None) -> Procedure:
    """lists: parameters that are lists, with the column names of their rows. into: a procedure to extend (delta exploration)."""
    began, lists = time.perf_counter(), lists or {}
    out = into or Procedure(fn.__name__, tuple(list(inspect.signature(fn).parameters)[1:]), Node(signal=f"{fn.__name__}-0"))
    queue, seen = [dict(seed or {})], set()
    while queue and out.runs < max_paths and time.perf_counter() - began < timeout_s:
        values = queue.pop()
        trace = run_once(fn, values, lists)
        decisions = _decisions(trace)
        signature = tuple(decisions)
        if signature in seen:
            continue
        seen.add(signature)
        out.runs += 1
        _merge(out.tree, trace, fn.__name__)
        for k in range(len(decisions)):
            wanted = [*decisions[:k], (decisions[k][0], not decisions[k][1])]
            if tuple(wanted) in {s[: k + 1] for s in seen}:
                continue
            verdict, found = solve(wanted, values)
            if verdict == "sat":
                queue.append(found)
            elif verdict == "unsat":
                _close(out.tree, wanted)
    out.seconds += time.perf_counter() - began
    return out


def _close(node: Node, decisions: list) -> None:
    """An infeasible side does nothing and is no signal."""
    sides = iter(decisions)
    left = len(decisions)

    def walk(node):
        nonlocal left
        for body in node.loops():
            if left:
                walk(body)
        if left and node.test is not None:
            _, side = next(sides)
            left -= 1
            child = node.yes if side else node.no
            if not left:
                child.signal = None
            else:
                walk(child)

    walk(node)


def slice_db_effects(node: Node) -> Node:
    """Without reads that nothing uses, and without branches whose sides do the same."""
    if node.test:
        yes, no = slice_db_effects(node.yes), slice_db_effects(node.no)
        if yes == no:
            return _pruned(Node([*node.steps, *yes.steps], yes.test, yes.yes, yes.no, yes.signal))
        return Node(node.steps, node.test, yes, no, node.signal)
    return _pruned(node)


def _pruned(node: Node) -> Node:
    if node.test:
        return node
    used, kept = set(), []
    for s in reversed(node.steps):
        if s[0] == "loop":
            body = slice_db_effects(s[2])
            if not body.steps and not body.test and not body.signal:
                continue
            s = ("loop", s[1], body)
        if s[0] in ("read", "exists", "native") and s[1] not in used:
            continue
        kept.append(s)
        used |= set().union(*(_names(e) for e in _expressions(s)))
        used |= _used(s[2]) if s[0] == "loop" else set()
    return Node(kept[::-1], signal=node.signal)


def _used(node: Node) -> set[str]:
    """Names that any step or test below needs."""
    out = set().union(*(_names(e) for s in node.steps for e in _expressions(s)), *(_used(body) for body in node.loops()))
    return out | _names(node.test) | _used(node.yes) | _used(node.no) if node.test else out


def _expressions(step: tuple) -> list:
    if step[0] == "loop":
        return [step[1]]
    if step[0] == "read":
        return list(step[3])
    if step[0] == "exists":
        return list(step[3])
    if step[0] == "write":
        return [*step[2], step[4]]
    if step[0] == "delete":
        return list(step[2])
    return list(step[3]) if step[0] == "native" else []


# ---- emitters --------------------------------------------------------------------------------------------------------


def _py(e) -> str:
    if e[0] == "lit":
        return repr(e[1])
    if e[0] == "var":
        return f"v[{e[1]!r}]"
    if e[0] == "item":
        return f"row[{e[1]!r}]"
    if e[1] in ("not", "neg"):
        return f"({'not ' if e[1] == 'not' else '-'}{_py(e[2])})"
    op = {"=": "==", "<>": "!=", "||": "+"}.get(e[1], e[1])
    a, b = (_py(x) for x in e[2:])
    return f"(str({a}) + str({b}))" if e[1] == "||" else f"({a} {op} {b})"


def python_source(p: Procedure) -> str:
    out = [f"def {p.name}(db, v, native):"]

    def steps(items, pad):
        for s in items:
            key = lambda k: "(" + "".join(_py(x) + ", " for x in k) + ")"
            if s[0] == "read":
                out.append(f"{pad}v[{s[1]!r}] = db.read({s[2]!r}, {key(s[3])}, {s[4]!r})")
            elif s[0] == "exists":
                out.append(f"{pad}v[{s[1]!r}] = db.exists({s[2]!r}, {key(s[3])})")
            elif s[0] == "write":
                out.append(f"{pad}db.write({s[1]!r}, {key(s[2])}, {s[3]!r}, {_py(s[4])})")
            elif s[0] == "delete":
                out.append(f"{pad}db.delete({s[1]!r}, {key(s[2])})")
            elif s[0] == "native":
                out.append(f"{pad}v[{s[1]!r}] = native({s[2]!r}, {', '.join(_py(x) for x in s[3])})")
            elif s[0] == "loop":
                out.append(f"{pad}for row in {_py(s[1])}:")
                emit(s[2], len(pad) // 4 + 1)

    def emit(node, depth):
        pad = "    " * depth
        steps(node.steps, pad)
        if node.signal:
            out.append(f"{pad}raise Signalled({node.signal!r})")
        elif node.test:
            out.append(f"{pad}if {_py(node.test)}:")
            emit(node.yes, depth + 1)
            out.append(f"{pad}else:")
            emit(node.no, depth + 1)
        else:
            out.append(f"{pad}pass")

    emit(p.tree, 1)
    return "\n".join(out) + "\n"


def to_python(p: Procedure) -> Callable:
    """A procedure `call(db, args, native)` that runs in one database call."""
    scope: dict = {"Signalled": Signalled}
    exec(compile(python_source(p), f"<procedure {p.name}>", "exec"), scope)
    body = scope[p.name]
    return lambda db, args, native=None: body(db, dict(args), native)


def _sql(e) -> str:
    if e[0] == "lit":
        return "NULL" if e[1] is None else "'" + e[1].replace("'", "''") + "'" if isinstance(e[1], str) else str(e[1])
    if e[0] in ("var", "item"):
        return f":{e[1]}"
    if e[1] in ("not", "neg"):
        return f"({'NOT ' if e[1] == 'not' else '-'}{_sql(e[2])})"
    return f"({_sql(e[2])} {e[1]} {_sql(e[3])})"


def to_sql_script(p: Procedure, keys: dict[str, tuple[str, ...]]) -> str:
    """The procedure as text that the SQL front end reads. keys: key columns of each table."""
    where = lambda t, k: " AND ".join(f"{c} = {_sql(x)}" for c, x in zip(keys[t], k, strict=True))

    def body(node, pad):
        out = []
        for s in node.steps:
            if s[0] in ("loop", "native"):
                raise ValueError(f"{p.name}: a {s[0]} has no form in SQL text; use the Python procedure")
            if s[0] == "read":
                out.append(f"{pad}SELECT {s[4]} INTO :{s[1]} FROM {s[2]} WHERE {where(s[2], s[3])};")
            elif s[0] == "exists":
                out.append(f"{pad}SELECT COUNT(*) INTO :{s[1]} FROM {s[2]} WHERE {where(s[2], s[3])};")
            elif s[0] == "write":
                out.append(f"{pad}INSERT INTO {s[1]} ({', '.join((*keys[s[1]], s[3]))}) VALUES ({', '.join(map(_sql, (*s[2], s[4])))}) ON CONFLICT ({', '.join(keys[s[1]])}) DO UPDATE SET {s[3]} = {_sql(s[4])};")
            elif s[0] == "delete":
                out.append(f"{pad}DELETE FROM {s[1]} WHERE {where(s[1], s[2])};")
        if node.signal:
            out.append(f"{pad}SIGNAL '{node.signal}';")
        elif node.test:
            out += [f"{pad}IF {_sql(node.test)} THEN", *body(node.yes, pad + "  "), f"{pad}ELSE", *body(node.no, pad + "  "), f"{pad}END IF;"]
        return out

    return "\n".join([f"CREATE PROCEDURE {p.name}({', '.join(p.params)}) BEGIN", *body(p.tree, "  "), "END"])


def to_columns(p: Procedure, args: dict[str, Column], reads: dict[tuple, Column]) -> dict[tuple, Column]:
    """Set-oriented form of a procedure without loops: (table, column) -> its new value, null where it is not written.

    args: a Column for each parameter; reads: a Column with the current value for each (table, column) read, and for each (table, None) tested."""
    out: dict[tuple, Column] = {}

    def column(e, env):
        if e[0] == "lit":
            return F.lit(e[1])
        if e[0] == "var":
            return env[e[1]]
        a = [column(x, env) for x in e[2:]]
        if e[1] in ("not", "neg"):
            return ~a[0] if e[1] == "not" else -a[0]
        return {"+": lambda x, y: x + y, "-": lambda x, y: x - y, "*": lambda x, y: x * y, "%": lambda x, y: x % y, "<": lambda x, y: x < y, "<=": lambda x, y: x <= y, ">": lambda x, y: x > y, ">=": lambda x, y: x >= y, "=": lambda x, y: x.eqNullSafe(y), "<>": lambda x, y: ~x.eqNullSafe(y), "||": lambda x, y: F.concat(x, y)}[e[1]](*a)

    def emit(node, guard, env):
        env = dict(env)
        now = dict(reads)
        for s in node.steps:
            if s[0] == "read":
                env[s[1]] = now[s[2], s[4]]
            elif s[0] == "exists":
                env[s[1]] = now[s[2], None]
            elif s[0] == "write":
                value = column(s[4], env)
                now[s[1], s[3]] = value
                old = out.get((s[1], s[3]), F.lit(None))
                out[s[1], s[3]] = F.when(guard, value).otherwise(old)
        if node.test:
            test = F.coalesce(column(node.test, env), F.lit(False))
            emit(node.yes, guard & test, env)
            emit(node.no, guard & ~test, env)

    emit(p.tree, F.lit(True), args)
    return out


# ---- running ---------------------------------------------------------------------------------------------------------


class Cells:
    """A database of cells, (table, key, column) -> value, that logs what it writes and counts calls."""

    def __init__(self, values: dict | None = None):
        self.values, self.written, self.calls = values if values is not None else {}, [], 0

    def read(self, table, key, column):
        self.calls += 1
        return self.values.get((table, _tuple(key), column), 0)

    def exists(self, table, key):
        self.calls += 1
        return (table, _tuple(key), None) in self.values

    def write(self, table, key, column, value):
        self.calls += 1
        key = _tuple(key)
        self.values[table, key, None] = True
        self.values[table, key, column] = value
        self.written.append((table, key, column, value))

    def delete(self, table, key):
        self.calls += 1
        key = _tuple(key)
        for cell in [c for c in self.values if c[0] == table and c[1] == key]:
            del self.values[cell]
        self.written.append((table, key, None, None))

    def native(self, name, *args):
        raise LookupError(f"no recorded value for {name}")

    def each(self, rows):
        yield from rows

    def call(self, target, known, *args):
        if target not in known:
            raise Signalled(f"unknown target {target}")
        return known[target](self, *args)


def check_equiv(fn: Callable, p: Procedure, inputs: list[tuple[dict, dict]], native: Callable | None = None) -> bool:
    """Whether function and procedure write the same for every (arguments, database) given."""
    call = to_python(p)
    for args, values in inputs:
        a, b = Cells(dict(values)), Cells(dict(values))
        if native:
            a.native = native
        fn(a, *(args[k] for k in p.params))
        call(b, args, native)
        if a.written != b.written or a.values != b.values:
            return False
    return True


def linked(client: Callable, server: Callable) -> Callable:
    """A client function and the server function that its request calls, as one function to explore. The client takes the page's inputs and gives
    the request's arguments, or None when it sends nothing, so its own checks become branches before the server's."""

    def both(db, *inputs):
        request = client(*inputs)
        if request is not None:
            server(db, *request)

    both.__name__ = f"{client.__name__}_{server.__name__}"
    names = list(inspect.signature(client).parameters)
    both.__signature__ = inspect.Signature([inspect.Parameter(n, inspect.Parameter.POSITIONAL_OR_KEYWORD) for n in ("db", *names)])
    return both


def checked(fn: Callable) -> list[str]:
    """What an application function does that exploration cannot follow: state outside the database, or calls that leave it unseen."""
    found, code = [], fn.__code__
    if any(i.opname in ("STORE_GLOBAL", "DELETE_GLOBAL") for i in dis.get_instructions(code)):
        found.append("writes a global variable")
    if any(i.opname == "STORE_DEREF" and i.argval in code.co_freevars for i in dis.get_instructions(code)):
        found.append("writes a variable of an enclosing function")
    outside = {"open", "exec", "eval", "input", "print"} & set(code.co_names)
    found += [f"calls {name}, which is no database call" for name in sorted(outside)]
    if code.co_flags & (inspect.CO_GENERATOR | inspect.CO_COROUTINE):
        found.append("is a generator or coroutine")
    if next(iter(inspect.signature(fn).parameters), "") != "db":
        found.append("does not take the database handle `db` first")
    return found


def delta_explore(fn: Callable, p: Procedure, witness: dict, lists: dict | None = None) -> Procedure:
    """Adds the path that a signal stood for, from the values that reached it."""
    return explore(fn, witness, lists, into=p)


def discover(module, predicate: Callable | None = None) -> list[Callable]:
    """Functions of a module whose first parameter is the database handle `db`, or those that the predicate names."""
    found = [f for _, f in inspect.getmembers(module, inspect.isfunction) if f.__module__ == module.__name__]
    return [f for f in found if (predicate(f) if predicate else next(iter(inspect.signature(f).parameters), "") == "db")]


def app_transaction(sink: Callable[[dict], None]):
    """Decorator that logs function name and arguments of each call before it runs."""

    def wrap(fn):
        names = list(inspect.signature(fn).parameters)[1:]

        def call(db, *args):
            sink({"app_fn": fn.__name__, "args": {k: str(a) for k, a in zip(names, args, strict=True)}})
            return fn(db, *args)

        call.__name__, call.__wrapped__ = fn.__name__, fn
        return call

    return wrap
