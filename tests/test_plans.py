"""Orders, costs and joins against enumeration and the worked numbers."""

import itertools
import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from docspj.model import Edge, JoinGraph, Leaf, Node, all_of, any_of, attributes_of, between, depth, eq, fuse_same_attribute, ge, isin, le, leaves, normalise, predicate, table
from docspj.operators.lazy import TokenModel, averages, fold_executor, in_selectivity, join_selectivity, ledger, observed, planned, round_executor, row_executor, selectivities
from docspj.plans.costs import SideStats, choose_side, combine, expected_flat, expected_walk, ideal_cost, in_cost, order_or_with_overlap, order_tree, pushdown_cost, sibling_orders, walk
from docspj.plans.ordering import sibling_permutations, walk_tables
from docspj.session import cut
from docspj.sqlfront import natural_language, parse

COSTS, CHANCES = st.sampled_from([1.0, 2.0, 5.0, 10.0, 20.0, 50.0]), st.floats(0.05, 0.95)


def random_tree(rng: random.Random, below: int, op: str = "and"):
    if below == 0:
        return eq(f"a{rng.randrange(10**9)}", 1)
    parts = [random_tree(rng, below - 1 if i == 0 else rng.randrange(below), "or" if op == "and" else "and") for i in range(rng.choice([2, 2, 3]))]
    return (all_of if op == "and" else any_of)(*parts)


@settings(max_examples=60, deadline=None)
@given(st.lists(st.tuples(COSTS, CHANCES), min_size=2, max_size=5), st.sampled_from(["and", "or"]))
def test_flat_order_is_the_best_of_all(filters, op):
    tree = normalise((all_of if op == "and" else any_of)(*[eq(f"a{i}", 0) for i in range(len(filters))]))
    cost, p = {f"a{i}": c for i, (c, _) in enumerate(filters)}, {i + 1: q for i, (_, q) in enumerate(filters)}
    best = min(expected_flat(op, [cost[f"a{i - 1}"] for i in o], [p[i] for i in o]) for o in itertools.permutations(p))
    assert order_tree(tree, cost, p).cost == pytest.approx(best)


@pytest.mark.parametrize("seed", range(25))
def test_tree_order_is_the_best_contiguous_one(seed):
    rng = random.Random(seed)
    tree = normalise(random_tree(rng, rng.choice([1, 2, 3])))
    every = leaves(tree)
    cost, p = {x.attr: rng.choice([1, 2, 5, 10, 20, 50]) for x in every}, {x.id: rng.uniform(0.05, 0.95) for x in every}
    ours = order_tree(tree, cost, p)
    assert ours.cost == pytest.approx(min(o.cost for o in sibling_orders(tree, cost, p)))
    assert ours.cost == pytest.approx(expected_walk(tree, ours.order, cost, p)) if len(every) <= 8 else True
    if depth(tree) <= 2 and len(every) <= 6:
        assert ours.cost == pytest.approx(min(expected_walk(tree, o, cost, p) for o in itertools.permutations([x.id for x in every])))


def test_deep_trees_may_have_better_scattered_orders():
    worse = 0
    for seed in range(40):
        rng = random.Random(seed)
        tree = normalise(all_of(any_of(eq("a", 1), eq("b", 1)), any_of(eq("c", 1), all_of(eq("d", 1), eq("e", 1)))))
        cost, p = {a: rng.choice([1, 2, 5, 10, 20, 50]) for a in "abcde"}, {i: rng.uniform(0.05, 0.95) for i in range(1, 6)}
        best = min(expected_walk(tree, o, cost, p) for o in itertools.permutations(range(1, 6)))
        ours = order_tree(tree, cost, p).cost
        assert best <= ours + 1e-9 and ours <= 1.3 * best
        worse += ours > best + 1e-9
    assert worse < 20


def test_worked_tree():
    tree = normalise(all_of(any_of(eq("a", 1), eq("b", 1)), any_of(eq("c", 1), all_of(eq("d", 1), eq("e", 1)))))
    cost = {"a": 1, "b": 5, "c": 20, "d": 60, "e": 30}
    assert order_tree(tree, cost, {1: 0.2, 2: 0.2, 3: 0.5, 4: 0.5, 5: 0.3}).order == (1, 2, 3, 5, 4)


def test_order_differs_by_document(spark):
    tree = normalise(all_of(ge("age", 36), ge("stars", 13)))
    docs = spark.createDataFrame([("d1", 20, 400), ("d2", 60, 55)], "doc_key string, c_age long, c_stars long")
    rows = planned(docs, tree, {"age": F.col("c_age"), "stars": F.col("c_stars")}, {1: 0.3, 2: 0.2}).collect()
    assert {r.doc_key: r.plan for r in rows} == {"d1": [1, 2], "d2": [2, 1]}


def test_nothing_to_read_comes_first_and_is_free(spark):
    tree = normalise(all_of(ge("a", 1), ge("b", 1)))
    docs = spark.createDataFrame([("d", 9, 0)], "doc_key string, ca long, cb long")
    c = {"a": F.col("ca"), "b": F.col("cb")}
    done = fold_executor(planned(docs, tree, c, {1: 0.5, 2: 0.9}), tree, {"a": F.lit(5), "b": F.lit(None).cast("int")}, c).first()
    assert (done.plan, done.tokens, done.calls, done.kept) == ([2, 1], 0, 0, False)


def test_overlap_of_a_disjunction():
    children = [eq("n", 1), ge("b", 2), eq("s", 3)]
    children = [Leaf(c.attr, c.op, c.args, i + 1) for i, c in enumerate(children)]
    assert order_or_with_overlap(children, {"s"}, {"n": 1, "b": 2, "s": 90}, {1: 0.9, 2: 0.5, 3: 0.1}) == (3, 1, 2)


def test_worked_join():
    t1, t2 = SideStats(30, 30 * 50, 0.1, 30 * 30), SideStats(51, 51 * 50, 0.3, 51 * 30)
    assert (t1.filter_cost, t1.p * t1.key_cost, t1.first_terms, t2.filter_cost, t2.p * t2.key_cost) == (1500, 90, 1590, 2550, 459)
    assert pushdown_cost(t1, t2) == 4599
    assert t2.with_in(0.1) == 1785 and in_cost(t1, t2, 0.1) == 3375
    assert t2.first_terms == 3009 and choose_side(t1, t2) == 0
    assert choose_side(t1, t2, "full", (0.1, 0.9)) == 0


SIDES = st.builds(SideStats, st.just(10), st.floats(0, 1e4), st.floats(0, 1), st.floats(0, 1e4))


@settings(max_examples=200, deadline=None)
@given(SIDES, SIDES, st.floats(0, 1), st.floats(0, 1))
def test_membership_filters_are_never_worse_than_pushdown(a, b, p, q):
    base = pushdown_cost(a, b)
    assert in_cost(a, b, p) <= base + 1e-6 and in_cost(b, a, q) <= base + 1e-6 and ideal_cost(a, b, q, p) <= base + 1e-6


def test_combined_chances():
    assert combine("and", [0.5, 0.2]) == pytest.approx(0.1) and combine("or", [0.5, 0.2]) == pytest.approx(0.6)


def test_three_executors_agree(spark):
    d = spark.read.parquet("/root/testdata/sf0.001/part.parquet")
    tree = normalise(all_of(any_of(eq("brand", "Brand#8"), ge("size", 40)), any_of(ge("price", 950), all_of(eq("type", "MEDIUM"), le("size", 25)))))
    v = {"brand": F.col("p_brand"), "size": F.col("p_size"), "price": F.col("p_retailprice"), "type": F.col("p_type")}
    c = {a: (F.col("p_partkey") * (7 + 2 * k) + 13 * k) % 50 for k, a in enumerate(v)}
    p = selectivities(d, tree, v)
    for mode in ("adaptive", "selectivity", "average_cost", "random", "written", "exhaustive"):
        rows = planned(d, tree, c, p, mode, averages=averages(d, c))
        fold = {r.p_partkey: (r.kept, r.tokens, r.calls) for r in fold_executor(rows, tree, {a: F.when(c[a] > 0, x) for a, x in v.items()}, c).collect()}
        if mode == "adaptive":
            ours = sum(x[1] for x in fold.values())
            wide = rows.select("p_partkey", "plan", *[v[a].cast("string").alias(f"x_{a}") for a in v], *[c[a].alias(f"c_{a}") for a in c])
            read = lambda a, t: float(t) if a in ("size", "price") else t
            by_row = row_executor(wide, tree, {a: f"x_{a}" for a in v}, {a: f"c_{a}" for a in c}, read, ["p_partkey"])
            assert {r.p_partkey: (r.kept, r.tokens, r.calls) for r in by_row.collect()} == fold
            batch = lambda rows: rows.select("p_partkey", "attr", F.col("text").alias("value"))
            number, plain = (lambda x: x.try_cast("double")), (lambda x: x)
            wide = wide.withColumns({f"x_{a}": F.when(F.col(f"c_{a}") > 0, F.col(f"x_{a}")) for a in v})
            rounds = round_executor(wide, "p_partkey", tree, {a: f"x_{a}" for a in v}, {a: f"c_{a}" for a in c}, batch, {a: number if a in ("size", "price") else plain for a in v}, cut)
            assert {r.p_partkey: (r.kept, r.tokens, r.calls) for r in rounds.collect()} == fold
        if mode == "exhaustive":
            assert sum(x[1] for x in fold.values()) == ours
        for r in rows.select("p_partkey", "plan", *[x.alias(a) for a, x in v.items()], *[x.alias(f"c_{a}") for a, x in c.items()]).limit(30).collect():
            truth = {x.id: bool(r[f"c_{x.attr}"]) and {"=": lambda a, b: a == b, ">=": lambda a, b: a >= b, "<=": lambda a, b: a <= b}[x.op](r[x.attr], x.args[0]) for x in leaves(tree)}
            kept, tested = walk(tree, r.plan, truth)
            first = dict.fromkeys(next(y.attr for y in leaves(tree) if y.id == i) for i in tested)
            assert fold[r.p_partkey][:2] == (kept, sum(r[f"c_{a}"] for a in first))


def test_model_and_parser():
    q = parse("SELECT customer.name, nation.name FROM customer JOIN nation ON customer.nation_name = nation.name WHERE customer.balance >= 9000 AND (nation.region_name = 'AFRICA' OR nation.n_customers BETWEEN 3 AND 5)")
    assert q.tables == ("customer", "nation") and q.edges == (Edge("customer", "nation_name", "nation", "name"),)
    assert q.where["customer"] == ge("balance", 9000) and q.where["nation"] == any_of(eq("region_name", "AFRICA"), between("n_customers", 3, 5))
    one = parse("select a from t where x = 1 or y < 2 and z in ('p', 'it''s') and not_flag = true")
    assert one.where["t"] == any_of(eq("x", 1), all_of(Leaf("y", "<", (2,)), isin("z", ["p", "it's"]), eq("not_flag", True)))
    assert parse("select a from t where 3 <= x").where["t"] == ge("x", 3)
    for bad in ("select from t", "select a from t where", "select a from t where x = 1 or", "select a from t join u on x = y", "select a from t where t.x = 1 or u.y = 2 extra"):
        with pytest.raises((SyntaxError, IndexError)):
            parse(bad)
    assert natural_language("all of it", lambda t: "select a from t").select == (("t", "a"),)
    built = table("customer").where(ge("balance", 9000)).select("name", "nation.name").join("nation", ("nation_name", "name")).where(eq("region_name", "AFRICA")).build()
    assert built.where["nation"] == eq("region_name", "AFRICA") and built.graph.tables == ("customer", "nation")
    tree = normalise(all_of(all_of(eq("a", 1), eq("b", 2)), any_of(eq("a", 3), eq("c", 4))))
    assert [x.id for x in leaves(tree)] == [1, 2, 3, 4] and isinstance(tree, Node) and len(tree.children) == 3
    assert fuse_same_attribute(tree) == [[1, 3], [2], [4]] and attributes_of(tree) == ["a", "b", "c"]
    assert len(sibling_permutations(tree)) == 12
    with pytest.raises(ValueError):
        JoinGraph.of(["a", "b", "c"], [Edge("a", "x", "b", "x")])


def test_missing_values_satisfy_nothing(spark):
    rows = spark.createDataFrame([(1, None), (2, 5)], "k int, v int")
    tree = any_of(eq("v", 5), between("v", 7, 9), isin("v", []))
    assert [r.k for r in rows.where(predicate(tree, {"v": F.col("v")})).collect()] == [2]


def test_order_column_grows_with_the_tree(spark):
    tree = normalise(all_of(*[any_of(eq(f"a{i}", 1), eq(f"b{i}", 1)) for i in range(8)]))
    cost = {a: F.lit(3) + F.col("id") % 7 for a in attributes_of(tree)}
    plan = planned(spark.range(50), tree, cost, {x.id: 0.5 for x in leaves(tree)})
    assert plan.count() == 50 and all(len(r.plan) == 16 for r in plan.collect())
    assert "Exchange" not in plan._jdf.queryExecution().executedPlan().toString()


def test_ledger_and_observation(spark):
    tree = normalise(all_of(ge("a", 5), ge("b", 1)))
    docs = spark.createDataFrame([("x", 9, 2, 3, 40), ("y", 1, 2, 3, 40), ("z", 9, None, 3, 0)], "doc_key string, a int, b int, ca long, cb long")
    v, c = {"a": F.col("a"), "b": F.col("b")}, {"a": F.col("ca"), "b": F.col("cb")}
    done, seen = observed(fold_executor(planned(docs, tree, c, {1: 0.5, 2: 0.9}), tree, v, c), "run")
    rows = {(r.doc_key, r.attr): (r.tokens_in, r.tokens_out, r.calls) for r in ledger(done, "doc_key", c, v, model=TokenModel(prompt=7)).collect()}
    assert rows == {("x", "a"): (10, 1, 1), ("x", "b"): (47, 1, 1), ("y", "a"): (10, 1, 1), ("z", "b"): (0, 0, 0)}
    assert seen.get == {"tokens": 46, "calls": 3, "kept": 1}
    values = spark.createDataFrame([(9,), (9,)], "value int")
    assert in_selectivity(docs, "a", values) == pytest.approx(2 / 3) and join_selectivity(docs.limit(0), "a", docs, "a") == 0.0


def test_tables_of_a_walk_are_its_states():
    """A state's number says which leaves are open, and which turn reads an attribute that no known leaf has read."""
    tree = normalise(any_of(eq("a", 1), all_of(eq("b", 2), eq("a", 3))))
    live, reads = walk_tables(tree, ["a", "b"])
    at = lambda state, i: state * 3 + i - 1
    assert [live[at(0, i)] for i in (1, 2, 3)] == [True] * 3 and [reads[at(0, i)] for i in (1, 2, 3)] == [1, 2, 1]
    assert not any(live[at(2, i)] for i in (1, 2, 3))
    assert [live[at(1, i)] for i in (1, 2, 3)] == [False, True, True] and [reads[at(1, i)] for i in (1, 2, 3)] == [0, 2, 0]
    assert [live[at(3, i)] for i in (1, 2, 3)] == [True, False, False]
