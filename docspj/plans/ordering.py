"""An order of filters for each document as one Column, by this engine's rule and the rules it is compared with."""

from __future__ import annotations

import hashlib
import itertools
from collections.abc import Iterable
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

from docspj.model import Expr, Leaf, Node, leaves
from docspj.plans.costs import order_tree

ARMS = ("written", "random", "selectivity", "average_cost", "exhaustive", "adaptive")


def priority_and(p: Column, c: Column) -> Column:
    return F.when(c > 0, (1 - p) / c).otherwise(F.lit(float("inf")))


def priority_or(p: Column, c: Column) -> Column:
    return F.when(c > 0, p / c).otherwise(F.lit(float("inf")))


def _node(i: Column, c: Column, p: Column, order: Column) -> Column:
    return F.struct(i.alias("id"), c.alias("c"), p.alias("p"), order.alias("order"))


def plan_node(expr: Expr, cost: dict[str, Column], p: dict[int, float]) -> Column:
    """struct(id, c, p, order) of the best contiguous order. Each child's expression appears once, so the plan grows with the tree alone."""
    def leaf(x: Leaf) -> tuple[Column, Column]:
        c = cost[x.attr].cast("double")
        return c, F.when(c > 0, F.lit(float(p[x.id]))).otherwise(0.0)

    if isinstance(expr, Leaf):
        c, q = leaf(expr)
        return _node(F.lit(expr.id), c, q, F.array(F.lit(expr.id)))
    rank = priority_and if expr.op == "and" else priority_or

    def ranked(x: Expr) -> Column:
        # A leaf's cost is a column or little more and may stand there again; what is below a node stands there once.
        if isinstance(x, Leaf):
            c, q = leaf(x)
            return F.struct((-rank(q, c)).alias("rank"), F.lit(x.id).alias("id"), plan_node(x, cost, p).alias("node"))
        return F.element_at(F.transform(F.array(plan_node(x, cost, p)), lambda n: F.struct((-rank(n["p"], n["c"])).alias("rank"), n["id"].alias("id"), n.alias("node"))), 1)

    keyed = F.array(*[ranked(x) for x in expr.children])
    start = F.struct(F.lit(0.0).alias("c"), F.lit(1.0).alias("reach"), F.array().cast("array<int>").alias("order"))

    def step(done: Column, x: Column) -> Column:
        n = x["node"]
        through = n["p"] if expr.op == "and" else 1 - n["p"]
        return F.struct((done["c"] + done["reach"] * n["c"]).alias("c"), (done["reach"] * through).alias("reach"), F.concat(done["order"], n["order"]).alias("order"))

    first = min(x.id for x in leaves(expr))
    finish = lambda done: _node(F.lit(first), done["c"], done["reach"] if expr.op == "and" else 1 - done["reach"], done["order"])
    return F.aggregate(F.sort_array(keyed), start, step, finish)


def expected_in_order(expr: Expr, order: Iterable[int], cost: dict[str, Column], p: dict[int, float]) -> Column:
    """Expected tokens of a given contiguous order of the tree's leaves."""

    def of(e: Expr) -> tuple[Column, Column, int]:
        if isinstance(e, Leaf):
            c = cost[e.attr].cast("double")
            return c, F.when(c > 0, F.lit(float(p[e.id]))).otherwise(0.0), rank[e.id]
        total, reach = F.lit(0.0), F.lit(1.0)
        parts = sorted((of(c) for c in e.children), key=lambda x: x[2])
        for c, q, _ in parts:
            total, reach = total + reach * c, reach * (q if e.op == "and" else 1 - q)
        return total, reach if e.op == "and" else 1 - reach, parts[0][2]

    rank = {i: n for n, i in enumerate(order)}
    return of(expr)[0]


def sibling_permutations(expr: Expr) -> list[tuple[int, ...]]:
    if isinstance(expr, Leaf):
        return [(expr.id,)]
    below = [sibling_permutations(c) for c in expr.children]
    return [sum(parts, ()) for choice in itertools.product(*below) for parts in itertools.permutations(choice)]


def expected_flat_order(expr: Node, order: Column, cost: Column, p: Column) -> Column:
    """Expected tokens of an order column of a flat tree; cost and p are arrays by leaf id."""
    through = lambda i: F.element_at(p, i) if expr.op == "and" else 1 - F.element_at(p, i)
    start = F.struct(F.lit(0.0).alias("c"), F.lit(1.0).alias("reach"))
    step = lambda s, i: F.struct((s["c"] + s["reach"] * F.element_at(cost, i)).alias("c"), (s["reach"] * through(i)).alias("reach"))
    return F.aggregate(order, start, step, lambda s: s["c"])


def _constant(order: Iterable[int]) -> Column:
    return F.array(*[F.lit(i) for i in order])


def order_column(
    expr: Expr, cost: dict[str, Column], p: dict[int, float], mode: str = "adaptive", averages: dict[str, float] | None = None, seed: str = "0", selected: Iterable[str] = (), most_orders: int = 5040
) -> Column:
    """array<int> of leaf ids in the order a document tests them.

    adaptive: cost and selectivity of each document. average_cost: the same rule on the sample's averages, one order for all. selectivity: by
    selectivity alone. random: by seeded hash. written: as the query has it. exhaustive: the cheapest of all contiguous orders for each
    document, at most `most_orders`. A pure disjunction that selects attributes it filters on tests these first.
    """
    every = leaves(expr)
    if mode == "written":
        return _constant(x.id for x in every)
    if mode == "random":
        return _constant(sorted((x.id for x in every), key=lambda i: hashlib.md5(f"{seed}:{i}".encode()).hexdigest()))
    if mode == "selectivity":
        return _constant(order_tree(expr, {x.attr: 1.0 for x in every}, p).order)
    if mode == "average_cost":
        return _constant(order_tree(expr, averages or {}, p).order)
    if mode == "exhaustive":
        orders = sibling_permutations(expr)
        if len(orders) > most_orders:
            raise ValueError(f"{len(orders)} orders are more than {most_orders}")
        priced = [F.struct(expected_in_order(expr, o, cost, p).alias("c"), _constant(o).alias("order")) for o in orders]
        return F.array_min(F.array(*priced))["order"]
    if mode != "adaptive":
        raise ValueError(f"unknown order {mode}")
    overlap = {x.id for x in every if x.attr in set(selected)}
    if isinstance(expr, Node) and expr.op == "or" and overlap and all(isinstance(c, Leaf) for c in expr.children):
        order = plan_node(expr, cost, p)["order"]
        return F.element_at(F.transform(F.array(order), lambda o: F.concat(F.filter(o, lambda i: i.isin(list(overlap))), F.filter(o, lambda i: ~i.isin(list(overlap))))), 1)
    return plan_node(expr, cost, p)["order"]


def node_value(expr: Expr, known: Column) -> Column:
    """1, 0, or -1 if undecided, of the tree under known: array by leaf id of 1, 0 or -1."""
    if isinstance(expr, Leaf):
        return F.element_at(known, expr.id)
    parts = [node_value(c, known) for c in expr.children]
    decided = 0 if expr.op == "and" else 1
    any_, all_ = (reduce(f, [x == v for x in parts]) for f, v in ((lambda a, b: a | b, decided), (lambda a, b: a & b, 1 - decided)))
    return F.when(any_, decided).when(all_, 1 - decided).otherwise(-1)


def open_leaves(expr: Expr, known: Column) -> Column:
    """array<boolean> by leaf id: no part of the tree above the leaf is decided, nor the leaf."""
    found: dict[int, Column] = {}

    def walk(e: Expr, above: list[Column]) -> None:
        here = [*above, node_value(e, known) == -1]
        if isinstance(e, Leaf):
            found[e.id] = reduce(lambda a, b: a & b, here)
        else:
            for c in e.children:
                walk(c, here)

    walk(expr, [])
    return F.array(*[found[i] for i in sorted(found)])


def start_state(expr: Expr, attributes: list[str]) -> Column:
    return F.struct(
        F.array_repeat(F.lit(-1), len(leaves(expr))).alias("known"),
        F.array_repeat(F.lit(False), len(attributes)).alias("seen"),
        F.lit(0).cast("bigint").alias("tokens"),
        F.lit(0).alias("calls"),
    )


def step_state(expr: Expr, attributes: list[str], state: Column, i: Column, truth: list[Column], cost: Column) -> Column:
    """The state after leaf i's turn: skipped if decided, free if its attribute was read before or has nothing to read.

    truth has a Column for each leaf; only leaf i's, and only if it is open, is evaluated.
    """
    place = F.lit([attributes.index(x.attr) + 1 for x in leaves(expr)])
    a = F.element_at(place, i)
    live = F.element_at(open_leaves(expr, state["known"]), i)
    read = live & ~F.element_at(state["seen"], a)
    price = F.element_at(cost, a)
    found = F.when(i == 1, truth[0])
    for k, t in enumerate(truth[1:], 2):
        found = found.when(i == k, t)
    return F.struct(
        F.when(live, F.transform(state["known"], lambda v, n: F.when(n + 1 == i, found.cast("int")).otherwise(v))).otherwise(state["known"]).alias("known"),
        F.when(read, F.transform(state["seen"], lambda v, n: v | (n + 1 == a))).otherwise(state["seen"]).alias("seen"),
        (state["tokens"] + F.when(read, price).otherwise(0)).cast("bigint").alias("tokens"),
        (state["calls"] + F.when(read & (price > 0), 1).otherwise(0)).alias("calls"),
    )


#: Trees of so many leaves are walked by tables of their states, 3 to the power of the leaves; larger ones by the states themselves.
MOST_TABLED = 6


def walk_tables(expr: Expr, attributes: list[str]) -> tuple[list[bool], list[int]]:
    """Of every state and leaf: whether the leaf is open, and the place of the attribute that its turn reads anew, or 0.

    A state is a number of base 3, a digit a leaf, the first the least: 0 unknown, 1 false, 2 true. What was read is what leaves are known. State s and leaf i are at s * n + i, from 1 on.
    """
    every = leaves(expr)
    live, reads = [], []
    for state in range(3 ** len(every)):
        known = {x.id: state // 3 ** (x.id - 1) % 3 for x in every}

        def value(e: Expr) -> int:
            if isinstance(e, Leaf):
                return known[e.id]  # noqa: B023
            parts, decided = [value(c) for c in e.children], 1 if e.op == "and" else 2
            return decided if decided in parts else 3 - decided if all(p == 3 - decided for p in parts) else 0

        free: dict[int, bool] = {}

        def mark(e: Expr, above: bool) -> None:
            here = above and value(e) == 0
            if isinstance(e, Leaf):
                free[e.id] = here  # noqa: B023
            else:
                for c in e.children:
                    mark(c, here)

        mark(expr, True)
        seen = {x.attr for x in every if known[x.id]}
        live += [free[i] for i in range(1, len(every) + 1)]
        reads += [attributes.index(x.attr) + 1 if free[x.id] and x.attr not in seen else 0 for x in sorted(every, key=lambda x: x.id)]
    return live, reads


def fold(expr: Expr, attributes: list[str], order: Column, truth: list[Column], cost: Column) -> Column:
    """struct(known, seen, tokens, calls) after the walk: a leaf's truth, and so the reading in it, is evaluated at its turn or not at all."""
    every = leaves(expr)
    n = len(every)
    if n > MOST_TABLED or sorted(x.id for x in every) != list(range(1, n + 1)):
        return F.aggregate(order, start_state(expr, attributes), lambda s, i: step_state(expr, attributes, s, i, truth, cost))
    live, reads = walk_tables(expr, attributes)
    power = F.lit([3**k for k in range(n)])
    start = F.struct(F.lit(0).alias("state"), F.lit(0).cast("bigint").alias("tokens"), F.lit(0).alias("calls"))

    def step(s: Column, i: Column) -> Column:
        at = s["state"] * n + i
        found = F.when(i == 1, truth[0])
        for k, t in enumerate(truth[1:], 2):
            found = found.when(i == k, t)
        digit = F.when(F.coalesce(found, F.lit(False)), 2).otherwise(1)
        price = F.coalesce(F.try_element_at(cost, F.nullif(F.element_at(F.lit(reads), at), F.lit(0))), F.lit(0).cast("bigint"))
        return F.struct(
            (s["state"] + F.when(F.element_at(F.lit(live), at), digit * F.element_at(power, i)).otherwise(0)).alias("state"),
            (s["tokens"] + price).cast("bigint").alias("tokens"),
            (s["calls"] + F.when(price > 0, 1).otherwise(0)).alias("calls"),
        )

    def finish(s: Column) -> Column:
        digits = [F.floor(s["state"] / 3**k).cast("int") % 3 - 1 for k in range(n)]
        seen = [reduce(lambda a, b: a | b, [digits[x.id - 1] >= 0 for x in every if x.attr == a]) for a in attributes]
        return F.struct(F.array(*digits).alias("known"), F.array(*seen).alias("seen"), s["tokens"].alias("tokens"), s["calls"].alias("calls"))

    return F.aggregate(order, start, step, finish)
