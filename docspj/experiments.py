"""The experiments: methods by suite, orderings, joins, ablations. Each returns plain rows (dicts) that a report prints."""

from __future__ import annotations

import time
from collections.abc import Sequence
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from docspj.baselines import NAMES, baseline
from docspj.engine import Engine, Run, Settings, best_order
from docspj.metrics import cost_gap, macro, modelled_latency, scores, token_cost
from docspj.model import Query, all_of, eq, normalise, predicate
from docspj.operators.extractors import ExtractionCache
from docspj.operators.index import TwoLevelIndex
from docspj.plans.costs import order_tree, sibling_orders
from docspj.sources.corpora import specs, truth
from docspj.workload import SUITES, group, make_joins


def truth_of(spark: SparkSession, sf_dir: str, q: Query) -> DataFrame:
    """The query's true tuples from the base columns."""
    parts = None
    for t in q.tables:
        rows = truth(spark, sf_dir, t)
        rows = rows.where(predicate(q.where.get(t), {c: F.col(c) for c in rows.columns}))
        own = rows.select(*[F.col(c).alias(f"{t}.{c}") for c in rows.columns if c != "doc_key"])
        if parts is None:
            parts = own
            continue
        links = [e for e in q.edges if t in (e.left, e.right) and f"{e.other(t)[1]}.{e.other(t)[2]}" in parts.columns]
        parts = parts.join(own, [F.col(f"`{e.left}.{e.left_attr}`") == F.col(f"`{e.right}.{e.right_attr}`") for e in links])
    return parts.select(*[F.col(f"`{t}.{a}`").alias(f"{t}.{a}" if len(q.tables) > 1 else a) for t, a in q.select])


def measure(spark: SparkSession, sf_dir: str, q: Query, run: Run, seconds: float) -> dict:
    tuples = run.tuples.select(*[f"`{c}`" for c in truth_of(spark, sf_dir, q).columns]) if len(q.tables) == 1 else run.tuples.toDF(*[f"{t}.{a}" for t, a in q.select])
    s = scores(tuples, truth_of(spark, sf_dir, q)).first()
    return {"precision": s["precision"], "recall": s["recall"], "f1": s["f1"], "tokens": token_cost(run.total, run.docs), "seconds": seconds / max(1, run.docs), "modelled_seconds": modelled_latency(run.calls, run.total, run.docs)}


def compare_methods(spark: SparkSession, sf_dir: str, index: TwoLevelIndex, suite: str = "P", methods: Sequence[str] = NAMES, queries: Sequence[Query] | None = None, regime: str = "pattern") -> list[dict]:
    """Accuracy, tokens and latency of each method, over all queries and by number of filters."""
    rows = []
    for m in methods:
        runner, by = baseline(m, index, specs(suite, regime)), {}
        for q in queries or SUITES[suite]():
            began = time.perf_counter()
            run = runner.run(q)
            by.setdefault(group(q), []).append(measure(spark, sf_dir, q, run, time.perf_counter() - began))
        every = [x for xs in by.values() for x in xs]
        rows.append({"method": m, "group": "all", **macro(every)})
        rows += [{"method": m, "group": g, **macro(xs)} for g, xs in sorted(by.items())]
    return rows


def compare_orders(index: TwoLevelIndex, suite: str, queries: Sequence[Query], orders: Sequence[str] = ("random", "selectivity", "average_cost", "adaptive", "exhaustive"), retrieval: str = "located") -> list[dict]:
    """Tokens a document of each way of ordering filters, by number of filters."""
    rows = []
    for o in orders:
        engine, by = Engine(index, specs(suite), Settings(retrieval=retrieval, order=o)), {}
        for q in queries:
            run = engine.run(q)
            by.setdefault(group(q), []).append({"tokens": token_cost(run.total, run.docs)})
        rows += [{"order": o, "group": g, **macro(xs)} for g, xs in sorted(by.items())]
    return rows


def planning_time(sizes: Sequence[int] = (2, 3, 4, 5, 6, 7, 8), large: Sequence[int] = (16, 32, 64)) -> list[dict]:
    """Seconds to order one document's filters, by priority and by listing all orders."""
    rows = []
    for m in (*sizes, *large):
        tree = normalise(all_of(*[eq(f"a{i}", 0) for i in range(m)]))
        cost, p = {f"a{i}": 5.0 + (i * 7) % 11 for i in range(m)}, {i + 1: ((i * 13) % 17 + 1) / 19 for i in range(m)}
        began = time.perf_counter()
        best = order_tree(tree, cost, p)
        ours = time.perf_counter() - began
        listed = None
        if m in sizes:
            began = time.perf_counter()
            least = min(sibling_orders(tree, cost, p), key=lambda x: x.cost)
            listed = time.perf_counter() - began
            assert abs(least.cost - best.cost) < 1e-9
        rows.append({"filters": m, "priority": ours, "exhaustive": listed})
    return rows


def compare_joins(index: TwoLevelIndex, edges: Sequence[Sequence[str]], n: int, modes: Sequence[str] = ("random", "pushdown", "adaptive", "optimal"), retrieval: str = "located") -> list[dict]:
    """Tokens a document of each way of joining, a query at a time: two tables where an entry of `edges` is one edge, more where it is several."""
    rows = []
    for group_edges in edges:
        for q in make_joins(group_edges, n):
            row = {"query": q.name, "group": group(q)}
            for m in modes:
                engine = Engine(index, specs("P"), Settings(retrieval=retrieval, join="adaptive" if m == "optimal" else m))
                run = best_order(engine, q) if m == "optimal" else engine.run(q)
                row[m] = run.total
                if m == "adaptive":
                    row["share"] = run.shares[0]
            rows.append(row)
    return rows


def by_in_selectivity(rows: Sequence[dict]) -> dict[str, dict]:
    """The rows of compare_joins regrouped by the share of the second side's sample that the first membership filter of the adaptive run lets through."""
    bins: dict[str, list[dict]] = {"0-0.3": [], "0.3-0.6": [], "0.6-1": []}
    for r in rows:
        x = r["share"]
        bins["0-0.3" if x < 0.3 else "0.3-0.6" if x < 0.6 else "0.6-1"].append({k: v for k, v in r.items() if k not in ("query", "group")})
    return {k: macro(v) for k, v in bins.items()}


def _ablate(spark: SparkSession, sf_dir: str, index: TwoLevelIndex, queries: Sequence[Query], changes: dict[str, dict], regime: str = "pattern") -> list[dict]:
    rows = []
    for name, change in changes.items():
        engine, found = Engine(index, specs("P", regime), replace(Settings(), **change)), []
        for q in queries:
            began = time.perf_counter()
            run = engine.run(q)
            found.append(measure(spark, sf_dir, q, run, time.perf_counter() - began) | {"total": run.total})
        rows.append({"arm": name, **macro(found)})
    return rows


def ablate_index(spark, sf_dir, index, queries, **k) -> list[dict]:
    return _ablate(spark, sf_dir, index, queries, {"two_level": {}, "segments_only": {"two_level": False}}, **k)


def ablate_evidence(spark, sf_dir, index, queries, **k) -> list[dict]:
    return _ablate(spark, sf_dir, index, queries, {"document": {}, "none": {"retrieval": "description"}, "synthetic": {"retrieval": "synthetic"}}, **k)


def ablate_tau(spark, sf_dir, index, queries, shifts: Sequence[float] = (-0.2, -0.1, 0.0, 0.1, 0.2), **k) -> list[dict]:
    """Radii about the one that each query's sample gives."""
    return _ablate(spark, sf_dir, index, queries, {f"tau{x:+.1f}": {"tau_shift": x} for x in shifts}, **k)


def ablate_rate(spark, sf_dir, index, queries, rates: Sequence[float] = (0.01, 0.03, 0.05, 0.1, 0.2), **k) -> list[dict]:
    return _ablate(spark, sf_dir, index, queries, {f"rate={r}": {"rate": r} for r in rates}, **k)


def ablate_k(spark, sf_dir, index, queries, ks: Sequence[int] = (1, 2, 3, 5, 8), **k) -> list[dict]:
    return _ablate(spark, sf_dir, index, queries, {f"k={x}": {"k": x} for x in ks}, **k)


def gamma_modes(spark, sf_dir, index, queries, **k) -> list[dict]:
    return _ablate(spark, sf_dir, index, queries, {"diameter": {}, "cluster": {"gamma_mode": "cluster"}}, **k)


def reuse(spark: SparkSession, index: TwoLevelIndex, first: Query, second: Query, path: str, retrieval: str = "located") -> dict:
    """Tokens of the second query alone, and after the first with a cache that both share."""
    suite = first.name[0]
    alone = Engine(index, specs(suite), Settings(retrieval=retrieval)).run(second)
    engine = Engine(index, specs(suite), Settings(retrieval=retrieval), cache=ExtractionCache(spark, path))
    engine.run(first)
    return {"alone": alone.total, "after": engine.run(second).total}


def expectation_gap(index: TwoLevelIndex, suite: str, queries: Sequence[Query], retrieval: str = "located") -> list[dict]:
    """Tokens that filters were expected to cost by their chances in the sample, independent of each other, and what they did."""
    engine, rows = Engine(index, specs(suite), Settings(retrieval=retrieval, measure_gap=True)), []
    for q in queries:
        run = engine.run(q)
        spent = run.tokens.get("filter", 0) + run.tokens.get("join", 0)
        rows.append({"query": q.name, "expected": run.expected, "spent": spent, "gap": cost_gap(run.expected, spent)})
    return rows


def report(rows: Sequence[dict]) -> str:
    """Rows as a Markdown table."""
    names = list(dict.fromkeys(k for r in rows for k in r))
    show = lambda v: f"{v:.4g}" if isinstance(v, float) else "" if v is None else str(v)
    return "\n".join(["| " + " | ".join(names) + " |", "|" + "---|" * len(names), *["| " + " | ".join(show(r.get(n)) for n in names) + " |" for r in rows]])
