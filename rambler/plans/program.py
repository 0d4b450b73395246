"""Weight programs: a weight expression in SQL text, its small expression tree, and what the analyzer derives from it.

Reserved columns of the text: h, label, dst (of the candidate edge); cur, prev, step, deg_cur, deg_prev, linked (of the walker's
step; linked: an edge leads from prev to the candidate); and the program's own parameters, which become literals.
"""

from __future__ import annotations

import itertools
import re
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np

EDGE_COLUMNS = frozenset({"h", "label", "dst", "idx"})
STEP_COLUMNS = frozenset({"cur", "prev", "step", "deg_cur", "deg_prev", "linked"})
_TOKEN = re.compile(r"\s*(\d+\.?\d*(?:[eE][+-]?\d+)?|\.\d+|[A-Za-z_]\w*|<>|!=|<=|>=|[-+*/%(),=<>])")
_COMPARE = {"=": "=", "<>": "<>", "!=": "<>", "<": "<", "<=": "<=", ">": ">", ">=": ">="}
#: Functions that grow with every argument, so bounds pass through them.
RISING = {"greatest": np.maximum.reduce, "least": np.minimum.reduce, "sqrt": lambda a: np.sqrt(a[0]), "ln": lambda a: np.log(a[0]), "exp": lambda a: np.exp(a[0])}


class UnboundableProgram(ValueError):
    """No upper bound can be derived: only reservoir sampling is safe."""


@dataclass(frozen=True)
class Node:
    kind: str  # num, var, op, fn, case
    value: object = None
    args: tuple = ()

    def variables(self) -> frozenset:
        return frozenset({self.value}) if self.kind == "var" else frozenset().union(*(a.variables() for a in self.args)) if self.args else frozenset()

    def sql(self) -> str:
        if self.kind == "num":
            return f"CAST({self.value!r} AS DOUBLE)"
        if self.kind == "var":
            return str(self.value)
        parts = [a.sql() for a in self.args]
        if self.kind == "fn":
            return f"{self.value}({', '.join(parts)})"
        if self.kind == "case":
            pairs = "".join(f" WHEN {c} THEN {v}" for c, v in zip(parts[0:-1:2], parts[1:-1:2]))
            return f"CASE{pairs} ELSE {parts[-1]} END"
        if self.value == "not":
            return f"(NOT {parts[0]})"
        if self.value == "isnull":
            return f"({parts[0]} IS NULL)"
        return f"(-{parts[0]})" if len(parts) == 1 else f"({f' {self.value} '.join(parts)})"

    def evaluate(self, env: dict):
        """Value in numpy; null is NaN or absent, and comparisons with it are false."""
        if self.kind == "num":
            return self.value
        if self.kind == "var":
            return env[self.value]
        got = [a.evaluate(env) for a in self.args]
        if self.kind == "fn":
            return RISING[self.value](got) if self.value in RISING else {"abs": np.abs, "power": np.power, "pow": np.power}[self.value](*got)
        if self.kind == "case":
            out = got[-1]
            for c, v in reversed(list(zip(got[0:-1:2], got[1:-1:2]))):
                out = np.where(c, v, out)
            return out
        a = got[0]
        if len(got) == 1:
            return np.logical_not(a) if self.value == "not" else a == -1 if self.value == "isnull" else -a
        b = got[1]
        return {"+": np.add, "-": np.subtract, "*": np.multiply, "/": np.divide, "%": np.mod, "=": np.equal, "<>": np.not_equal, "<": np.less, "<=": np.less_equal, ">": np.greater, ">=": np.greater_equal, "AND": np.logical_and, "OR": np.logical_or}[self.value](a, b)


def num(x: float) -> Node:
    return Node("num", float(x))


def op(name: str, *args: Node) -> Node:
    if name in "+-*/" and len(args) == 2 and all(a.kind == "num" for a in args):
        x, y = args[0].value, args[1].value
        return num({"+": x + y, "-": x - y, "*": x * y, "/": x / y if y else float("nan")}[name])
    if name == "*" and num(0) in args:
        return num(0)  # weights are finite
    if name == "*" and num(1) in args:
        return args[1] if args[0] == num(1) else args[0]
    return Node("op", name, args)


def parse(text: str, params: dict[str, float]) -> Node:
    """The tree of a weight expression, parameters replaced by their values."""
    tokens, at = [], 0
    while at < len(text.rstrip()):
        if not (m := _TOKEN.match(text, at)):
            raise UnboundableProgram(f"can't read {text[at:at + 20]!r}")
        tokens.append(m[1])
        at = m.end()
    tokens.append("")
    i = 0

    def peek() -> str:
        return tokens[i].upper()

    def take(expected: str | None = None) -> str:
        nonlocal i
        if expected and peek() != expected:
            raise UnboundableProgram(f"{expected} expected before {tokens[i]!r}")
        i += 1
        return tokens[i - 1]

    def chain(below, names):
        def level() -> Node:
            left = below()
            while peek() in names:
                left = op(take().upper(), left, below())
            return left

        return level

    def primary() -> Node:
        word = take()
        if re.match(r"[\d.]", word):
            return num(float(word))
        if word == "(":
            inner = either()
            take(")")
            return inner
        if word == "-":
            return op("-", num(0), primary())
        if word.upper() == "CASE":
            parts = []
            while peek() == "WHEN":
                take()
                parts.append(either())
                take("THEN")
                parts.append(either())
            take("ELSE")
            parts.append(either())
            take("END")
            return Node("case", None, tuple(parts))
        if peek() == "(" and re.match(r"[A-Za-z_]", word):
            take()
            args = []
            while peek() != ")":
                args.append(either())
                if peek() == ",":
                    take()
            take(")")
            if word.lower() == "if":
                return Node("case", None, tuple(args))
            return Node("fn", word.lower(), tuple(args))
        if word.lower() in params:
            return num(params[word.lower()])
        if not re.match(r"[A-Za-z_]", word):
            raise UnboundableProgram(f"unexpected {word!r}")
        return Node("var", word.lower())

    def compare() -> Node:
        left = total()
        if peek() == "IS":
            take()
            negated = peek() == "NOT" and bool(take())
            take("NULL")
            test = Node("op", "isnull", (left,))
            return Node("op", "not", (test,)) if negated else test
        if peek() in _COMPARE:
            return Node("op", _COMPARE[take()], (left, total()))
        return left

    def negation() -> Node:
        if peek() == "NOT":
            take()
            return Node("op", "not", (negation(),))
        return compare()

    product = chain(primary, {"*", "/", "%"})
    total = chain(product, {"+", "-"})
    both = chain(negation, {"AND"})
    either = chain(both, {"OR"})
    tree = either()
    if peek():
        raise UnboundableProgram(f"unexpected {tokens[i]!r}")
    return tree


def branches(tree: Node) -> list[tuple[str, Node]]:
    """(guard, value) of every leaf that the expression can return."""
    if tree.kind == "case":
        out, before = [], []
        for c, v in zip(tree.args[0:-1:2], tree.args[1:-1:2]):
            out += [(" AND ".join([*before, c.sql(), *([g] if g != "TRUE" else [])]), leaf) for g, leaf in branches(v)]
            before.append(f"NOT {c.sql()}")
        return out + [(" AND ".join([*before, *([g] if g != "TRUE" else [])]), leaf) for g, leaf in branches(tree.args[-1])]
    if not tree.args:
        return [("TRUE", tree)]
    rebuilt = []
    for choice in itertools.product(*(branches(a) for a in tree.args)):
        guard = " AND ".join(g for g, _ in choice if g != "TRUE") or "TRUE"
        args = tuple(leaf for _, leaf in choice)
        rebuilt.append((guard, op(tree.value, *args) if tree.kind == "op" else Node(tree.kind, tree.value, args)))
    return rebuilt


#: Statistics and step columns that are never below zero, and those that are above it.
NEVER_NEGATIVE, ALWAYS_POSITIVE = frozenset({"h", "h_min", "h_max", "h_sum", "step", "linked"}), frozenset({"deg_cur", "deg_prev"})


def at_least_zero(node: Node, strictly: bool = False) -> bool:
    """Whether the value is certain not to be negative (strictly: to be positive)."""
    if node.kind == "num":
        return node.value > 0 if strictly else node.value >= 0
    if node.kind == "var":
        return node.value in ALWAYS_POSITIVE or not strictly and node.value in NEVER_NEGATIVE
    if node.kind == "fn":
        if node.value == "greatest":
            return any(at_least_zero(a, strictly) for a in node.args)
        return node.value == "exp" or node.value in ("least", "sqrt") and all(at_least_zero(a, strictly) for a in node.args)
    if node.kind == "op" and node.value == "+" and len(node.args) == 2:
        return all(map(at_least_zero, node.args)) and (not strictly or any(at_least_zero(a, True) for a in node.args))
    if node.kind == "op" and node.value in "*/" and len(node.args) == 2:
        return at_least_zero(node.args[0], strictly) and at_least_zero(node.args[1], strictly or node.value == "/")
    return False


def _ends(name: str, *corners: Node) -> Node:
    """The least or greatest of some values."""
    different = tuple(dict.fromkeys(corners))
    if all(c.kind == "num" for c in different):
        return num((min if name == "least" else max)(c.value for c in different))
    return different[0] if len(different) == 1 else Node("fn", name, different)


def interval(node: Node) -> tuple[Node, Node]:
    """Least and greatest value over a node's edges, in the node's statistics. h is never negative; all else may have any sign, so that
    products and quotients take the extremes of their corners unless the signs are certain."""
    if node.kind == "num":
        return node, node
    if node.kind == "var":
        if node.value == "h":
            return Node("var", "h_min"), Node("var", "h_max")
        if node.value in EDGE_COLUMNS:
            raise UnboundableProgram(f"{node.value} has no bound in the statistics")
        return node, node
    ranges = [interval(a) for a in node.args]
    lows, highs = [r[0] for r in ranges], [r[1] for r in ranges]
    if node.kind == "fn":
        if node.value not in RISING:
            raise UnboundableProgram(f"{node.value}() isn't known to grow with its arguments")
        if node.value == "ln" and not at_least_zero(lows[0], True) or node.value == "sqrt" and not at_least_zero(lows[0]):
            raise UnboundableProgram(f"{node.value}() of what may be too small")
        return Node("fn", node.value, tuple(lows)), Node("fn", node.value, tuple(highs))
    if node.kind == "op" and len(node.args) == 2:
        (a, c), (b, d) = lows, highs
        if node.value == "+":
            return op("+", a, c), op("+", b, d)
        if node.value == "-":
            return op("-", a, d), op("-", b, c)
        if node.value == "*":
            if at_least_zero(a) and at_least_zero(c):
                return op("*", a, c), op("*", b, d)
            corners = [op("*", x, y) for x in (a, b) for y in (c, d)]
            return _ends("least", *corners), _ends("greatest", *corners)
        if node.value == "/":
            if not (at_least_zero(c, True) or c == d and c.kind == "num" and c.value < 0):
                raise UnboundableProgram("a divisor that may be zero or below")
            if at_least_zero(a) and at_least_zero(c, True):
                return op("/", a, d), op("/", b, c)
            corners = [op("/", x, y) for x in (a, b) for y in (c, d)]
            return _ends("least", *corners), _ends("greatest", *corners)
    raise UnboundableProgram(f"no bound through {node.value!r}")


def substitute(node: Node, name: str, by: Node) -> Node:
    if node.kind == "var":
        return by if node.value == name else node
    args = tuple(substitute(a, name, by) for a in node.args)
    return node if not args else op(node.value, *args) if node.kind == "op" else Node(node.kind, node.value, args)


@dataclass(frozen=True)
class Branch:
    branch_id: int
    guard: str
    value: str
    deps: tuple[str, ...]
    flag: str


@dataclass(frozen=True)
class Analysis:
    """branches: one row for each return value; flag: RUN if bound and estimate are fixed for the whole run, else STEP."""

    branches: tuple[Branch, ...]
    flag: str
    stats_needed: tuple[str, ...]
    bound: Node | None
    total: Node | None
    warnings: tuple[str, ...] = ()

    @property
    def bound_sql(self) -> str | None:
        return self.bound and self.bound.sql()

    @property
    def sum_sql(self) -> str | None:
        return self.total and self.total.sql()

    def rows(self) -> list[tuple]:
        return [(b.branch_id, b.guard, b.value, list(b.deps), b.flag) for b in self.branches]

    def to_frame(self, spark):
        return spark.createDataFrame(self.rows(), "branch_id int, guard string, value string, deps array<string>, flag string")


@dataclass(frozen=True)
class WeightProgram:
    """order 2: the previous node counts (the first step then has weight 1). weighted: multiplied by the edge's h."""

    name: str
    weight: str
    params: dict = field(default_factory=dict, hash=False)
    order: int = 1
    weighted: bool = True
    schema: tuple[int, ...] = ()
    depth: int | None = None

    @cached_property
    def tree(self) -> Node:
        return parse(self.weight, self.params)

    @cached_property
    def full(self) -> Node:
        """The transition weight, h and the first step's rule included."""
        inner = Node("case", None, (Node("op", "isnull", (Node("var", "prev"),)), num(1), self.tree)) if self.order == 2 else self.tree
        return op("*", inner, Node("var", "h")) if self.weighted else inner

    def sql(self) -> str:
        return self.full.sql()

    def needs(self, column: str) -> bool:
        return column in self.full.variables()

    @cached_property
    def analysis(self) -> Analysis:
        return analyze(self)

    def explain(self) -> str:
        a = self.analysis
        lines = [f"{self.name}: {self.sql()}", *(f"  [{b.branch_id}] {b.guard} -> {b.value}  ({', '.join(b.deps) or 'constants'}; {b.flag})" for b in a.branches)]
        return "\n".join([*lines, f"  flag: {a.flag}", f"  bound: {a.bound_sql}", f"  sum: {a.sum_sql}", *(f"  warning: {w}" for w in a.warnings)])


def _sloped(node: Node) -> bool:
    """h stands inside a sum or difference."""
    return node.kind == "op" and node.value in ("+", "-") and "h" in node.variables() or any(_sloped(a) for a in node.args)


def _over_all(leaf: Node) -> Node:
    """Estimate of a leaf's sum over the list: h_sum for h; the mean of h, times the degree, in sums; the degree alone without h."""
    degree = Node("var", "deg_cur")
    if _sloped(leaf):
        return op("*", substitute(leaf, "h", op("/", Node("var", "h_sum"), degree)), degree)
    return substitute(leaf, "h", Node("var", "h_sum")) if "h" in leaf.variables() else op("*", leaf, degree)


def analyze(program: WeightProgram) -> Analysis:
    """Bound and sum estimate of the transition weights of one node, from the branches' values (their guards don't matter)."""
    core = op("*", program.tree, Node("var", "h")) if program.weighted else program.tree
    leaves = branches(core)
    out, distinct = [], []
    for k, (guard, leaf) in enumerate(leaves):
        deps = tuple(sorted(leaf.variables()))
        out.append(Branch(k, guard, leaf.sql(), deps, "STEP" if leaf.variables() & (EDGE_COLUMNS | STEP_COLUMNS) else "RUN"))
        if leaf not in distinct:
            distinct.append(leaf)
    flag = "STEP" if any(b.flag == "STEP" for b in out) else "RUN"
    try:
        # The first step of a second-order program has weight 1 (times h), which the bound has to cover too.
        first = [Node("var", "h") if program.weighted else num(1)] if program.order == 2 else []
        highs = [interval(leaf)[1] for leaf in [*distinct, *(x for x in first if x not in distinct)]]
        constants = [x.value for x in highs if x.kind == "num"]
        bound = num(max(constants)) if len(constants) == len(highs) else highs[0] if len(highs) == 1 else Node("fn", "greatest", tuple(dict.fromkeys(highs)))
        parts = [_over_all(leaf) for leaf in distinct]
        total = parts[0]
        for p in parts[1:]:
            total = op("+", total, p)
        total = op("/", total, num(len(parts)))
    except UnboundableProgram as e:
        return Analysis(tuple(out), flag, (), None, None, (f"UnboundableProgram: {e}; the reservoir sampler is used",))
    needed = tuple(sorted((bound.variables() | total.variables()) & {"h_max", "h_min", "h_sum", "deg_cur", "deg_prev"}))
    return Analysis(tuple(out), flag, needed, bound, total)


def static_walk(weighted: bool = True) -> WeightProgram:
    return WeightProgram("static", "1", weighted=weighted)


def return_inout(a: float = 2.0, b: float = 0.5, weighted: bool = True) -> WeightProgram:
    """Second-order walk: 1/a back to the previous node, 1 to its neighbours, 1/b elsewhere."""
    return WeightProgram("return_inout", "CASE WHEN dst = prev THEN 1 / a WHEN linked THEN 1 ELSE 1 / b END", {"a": a, "b": b}, 2, weighted)


def meta_path(schema: tuple[int, ...] = (0, 1, 2, 3, 4), weighted: bool = True) -> WeightProgram:
    """Only edges whose label is the schema's at this step."""
    cases = " ".join(f"WHEN step = {i} AND label = {x} THEN 1" for i, x in enumerate(schema))
    return WeightProgram("meta_path", f"CASE {cases} ELSE 0 END", {}, 1, weighted, tuple(schema), len(schema))


def second_order_rank(gamma: float = 0.2, weighted: bool = True) -> WeightProgram:
    text = "CASE WHEN linked AND dst <> prev THEN ((1 - gamma) / deg_cur + gamma / deg_prev) * greatest(deg_cur, deg_prev) ELSE (1 - gamma) / deg_cur * greatest(deg_cur, deg_prev) END"
    return WeightProgram("second_order_rank", text, {"gamma": gamma}, 2, weighted)
