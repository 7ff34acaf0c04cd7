"""Lazy evaluation of a tree over documents with known costs: three executors of one meaning, and the token ledger."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from docspj.functions.text import n_tokens
from docspj.model import Expr, attributes_of, leaves, test, test_python
from docspj.plans.costs import relevant, value_of
from docspj.plans.ordering import fold, node_value, open_leaves, order_column, start_state, step_state


def selectivities(sample: DataFrame, expr: Expr, value: dict[str, Column], alpha: float = 0.0, truths: dict[int, Column] | None = None) -> dict[int, float]:
    """Share of the sample that satisfies each leaf, in one pass; alpha smooths zeros and ones."""
    every, truths = leaves(expr), truths or {}
    held = {x.id: truths[x.id] if x.id in truths else test(x, value[x.attr]) for x in every}
    row = sample.agg(F.count(F.lit(1)).alias("n"), *[F.coalesce(F.sum(held[x.id].cast("int")), F.lit(0)).alias(f"l{x.id}") for x in every]).first()
    n = row["n"] + 2 * alpha
    return {x.id: (row[f"l{x.id}"] + alpha) / n if n else 0.5 for x in every}


def averages(sample: DataFrame, cost: dict[str, Column]) -> dict[str, float]:
    row = sample.agg(*[F.coalesce(F.avg(c), F.lit(0.0)).alias(a) for a, c in cost.items()]).first()
    return row.asDict()


def planned(docs: DataFrame, expr: Expr, cost: dict[str, Column], p: dict[int, float], mode: str = "adaptive", **options) -> DataFrame:
    """docs with `plan`, the order each document tests its filters in."""
    return docs.withColumn("plan", order_column(expr, cost, p, mode, **options))


def fold_executor(docs: DataFrame, expr: Expr, value: dict[str, Column], cost: dict[str, Column], select: Iterable[str] = (), truths: dict[int, Column] | None = None) -> DataFrame:
    """docs(plan, ...) with `kept`, and `tokens`, `calls`, `select_tokens` of a lazy reader; no Python and no shuffle.

    SELECT attributes that no filter read are read for documents that are kept. `truths` stands for a leaf's own test, as for membership in a table.
    """
    attributes, truths = attributes_of(expr), truths or {}
    truth = [truths[x.id] if x.id in truths else test(x, value[x.attr]) for x in leaves(expr)]
    price = F.array(*[F.coalesce(cost[a], F.lit(0)).cast("bigint") for a in attributes])
    after = docs.withColumn("walk", fold(expr, attributes, F.col("plan"), truth, price)).withColumn("kept", node_value(expr, F.col("walk.known")) == 1)
    late = F.lit(0).cast("bigint")
    for a in dict.fromkeys(select):
        own = F.coalesce(cost[a], F.lit(0)).cast("bigint")
        late = late + (F.when(F.element_at("walk.seen", attributes.index(a) + 1), 0).otherwise(own) if a in attributes else own)
    names = F.lit(attributes)
    after = after.withColumn("read_attrs", F.filter(names, lambda a, i: F.element_at("walk.seen", i + 1)))
    return after.withColumns({"tokens": F.col("walk.tokens"), "calls": F.col("walk.calls"), "select_tokens": F.when(F.col("kept"), late).otherwise(0).cast("bigint")}).drop("walk")


@dataclass(frozen=True)
class TokenModel:
    """What a call costs besides the text it is given: a prompt, and its answer's own tokens."""

    prompt: int = 0
    count_output: bool = True


def ledger(done: DataFrame, key: str, cost: dict[str, Column], value: dict[str, Column], query: str = "", phase: str = "filter", model: TokenModel | None = None) -> DataFrame:
    """(query, key, attr, phase, tokens_in, tokens_out, calls) of what the fold executor read: a row a document and attribute."""
    model = model or TokenModel()
    priced = F.array(*[F.struct(F.lit(a).alias("attr"), F.coalesce(c, F.lit(0)).cast("bigint").alias("tokens"), (n_tokens(value[a].cast("string")) if model.count_output else F.lit(0)).cast("bigint").alias("out")) for a, c in cost.items()])
    rows = done.select(key, "read_attrs", F.inline(priced)).where(F.array_contains("read_attrs", F.col("attr")))
    called = F.col("tokens") > 0
    return rows.select(
        F.lit(query).alias("query"), key, "attr", F.lit(phase).alias("phase"),
        F.when(called, F.col("tokens") + model.prompt).otherwise(0).cast("bigint").alias("tokens_in"), F.when(called, F.col("out")).otherwise(0).cast("bigint").alias("tokens_out"), called.cast("int").alias("calls"),
    )


def observed(done: DataFrame, name: str) -> tuple[DataFrame, Observation]:
    """done, and its sums of tokens, calls and kept documents, gathered while it is computed for something else."""
    seen = Observation(name)
    return done.observe(seen, F.sum("tokens").alias("tokens"), F.sum("calls").alias("calls"), F.count_if("kept").alias("kept")), seen


def in_selectivity(sample: DataFrame, key: str, values: DataFrame) -> float:
    """Share of a sample whose key is among values(value)."""
    held = sample.join(values.select(F.col("value").alias("member")).distinct(), F.col(key) == F.col("member"), "left")
    return held.agg(F.avg(F.col("member").isNotNull().cast("double"))).first()[0] or 0.0


def join_selectivity(left: DataFrame, left_key: str, right: DataFrame, right_key: str) -> float:
    """Share of the right sample that meets a key of the left one: an estimate before anything is run."""
    return in_selectivity(right, right_key, left.select(F.col(left_key).alias("value")))


def row_executor(docs: DataFrame, expr: Expr, context: dict[str, str], cost: dict[str, str], extract: Callable[[str, str], object], keep: Iterable[str], parse: dict[str, Callable[[str], object]] | None = None, members: frozenset | None = None) -> DataFrame:
    """One pass over docs(plan, context and cost columns): extract(attribute, text) is called only when a test needs it.

    Returns the kept columns with kept, tokens, calls, and the map `values` of what is known of each document now, as text. Laziness is the loop's own, so it
    does not hang on how Spark orders expressions. docs may have a map `values` of what is known before; parse turns texts into values. With members
    the first leaf is membership in them: they go to every task, so the caller bounds them.
    """
    every, parse = {x.id: x for x in leaves(expr)}, parse or {}
    keep = [k for k in keep if k != "values"]
    before = "values" in docs.columns

    def of(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def typed(a: str, raw: object) -> object:
            return None if raw is None else parse[a](raw) if a in parse else raw

        for frame in batches:
            rows = []
            for r in frame.to_dict("records"):
                known, tokens, calls = {}, 0, 0
                values = dict(zip(r["known_names"], r["known_texts"], strict=True)) if before else {}
                for i in r["plan"]:
                    if value_of(expr, known) is not None:
                        break
                    if not relevant(expr, i, known):
                        continue
                    a = every[i].attr
                    if a not in values:
                        price = 0 if pd.isna(r[cost[a]]) else int(r[cost[a]])
                        tokens, calls = tokens + price, calls + (price > 0)
                        values[a] = extract(a, r[context[a]]) if price else None
                    value = typed(a, values[a])
                    known[i] = value is not None and value in members if members is not None and i == 1 else test_python(every[i], value)
                texts = [None if v is None else str(v) for v in values.values()]
                rows.append((*[r[k] for k in keep], list(values), texts, bool(value_of(expr, known)), tokens, calls))
            yield pd.DataFrame(rows, columns=[*keep, "known_names", "known_texts", "kept", "tokens", "calls"])

    asked = docs.withColumns({"known_names": F.map_keys("values"), "known_texts": F.map_values("values")}).drop("values") if before else docs
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema if f.name in keep)
    done = asked.mapInPandas(of, f"{fields}, known_names array<string>, known_texts array<string>, kept boolean, tokens long, calls int")
    return done.withColumn("values", F.map_from_arrays("known_names", "known_texts")).drop("known_names", "known_texts")


def round_executor(docs: DataFrame, key: str, expr: Expr, context: dict[str, str], cost: dict[str, str], batch: Callable[[DataFrame], DataFrame], parse: dict[str, Callable[[Column], Column]], cut: Callable[[DataFrame], DataFrame], members: DataFrame | None = None) -> DataFrame:
    """Rounds for batch endpoints: in each, every undecided document has its next filter's attribute read, all in one request table.

    batch: (key, attr, text) -> (key, attr, value). cut writes a round durably, so what was paid for is never read twice. At most as many rounds as leaves.
    docs may have a map `values` of what is known; what costs nothing is not asked for. With members(member), distinct values, the first leaf is
    membership in them, by a join: they may be many.
    """
    every, attributes = leaves(expr), attributes_of(expr)
    price = F.array(*[F.coalesce(F.col(cost[a]), F.lit(0)).cast("bigint") for a in attributes])
    known = F.col("values") if "values" in docs.columns else F.create_map().cast("map<string,string>")
    state = docs.withColumns({"state": start_state(expr, attributes), "values": known, "step": F.lit(0)})
    for _ in range(len(every)):
        live = lambda s, i: F.element_at(open_leaves(expr, s), i)
        upcoming = F.filter(F.slice("plan", F.col("step") + 1, F.greatest(F.size("plan") - F.col("step"), F.lit(0))), lambda i: live(F.col("state.known"), i))
        state = state.withColumn("next", F.try_element_at(upcoming, F.lit(1))).withColumn("attr", F.try_element_at(F.lit([x.attr for x in every]), "next"))
        waits = F.col("attr").isNotNull() & ~F.map_contains_key("values", F.coalesce("attr", F.lit("")))
        text = F.coalesce(*[F.when(F.col("attr") == a, F.col(context[a])) for a in attributes], F.lit(""))
        asked = state.where(waits & (F.element_at(price, F.array_position(F.lit(attributes), F.col("attr")).cast("int")) > 0))
        answers = cut(batch(asked.select(key, "attr", text.alias("text"))).select(F.col(key).alias("answered"), F.col("attr").alias("of"), "value"))
        joined = state.join(answers, (F.col(key) == F.col("answered")) & (F.col("attr") == F.col("of")), "left")
        values = F.when(waits, F.map_concat("values", F.map_from_arrays(F.array("attr"), F.array("value")))).otherwise(F.col("values"))
        joined = joined.withColumn("values", values).drop("answered", "of", "value")
        truth = [test(x, parse[x.attr](F.try_element_at("values", F.lit(x.attr)))) for x in every]
        if members is not None:
            joined = joined.join(members.select(F.col("member").alias("of")), parse[every[0].attr](F.try_element_at("values", F.lit(every[0].attr))) == F.col("of"), "left").withColumn("is_in", F.col("of").isNotNull()).drop("of")
            truth[0] = F.col("is_in")
        moved = F.when(F.col("next").isNotNull(), step_state(expr, attributes, F.col("state"), F.col("next"), truth, price)).otherwise(F.col("state"))
        state = cut(joined.withColumns({"state": moved, "step": F.coalesce(F.array_position("plan", F.col("next")).cast("int"), F.col("step"))}).drop("next", "attr", "is_in"))
    return state.withColumns({"kept": node_value(expr, F.col("state.known")) == 1, "tokens": F.col("state.tokens"), "calls": F.col("state.calls")}).drop("state", "step")
