"""The fixed query suites, a seeded generator of more, and which base columns they stand for."""

from __future__ import annotations

import hashlib
from collections.abc import Sequence

from docspj.model import Edge, Expr, Leaf, Query, all_of, any_of, between, eq, ge, isin, le, leaves

_CN = Edge("customer", "nation_name", "nation", "name")
_NR = Edge("nation", "region_name", "region", "name")
_NS = Edge("nation", "owner_name", "supplier", "name")


def _single(name: str, table: str, where: Expr, *select: str) -> Query:
    return Query(name, (table,), tuple((table, s) for s in select), {table: where})


def suite_p() -> list[Query]:
    c, p, s, n = "customer", "part", "supplier", "nation"
    seg, bal, nat = (lambda v: eq("segment", v)), (lambda v: ge("balance", v)), (lambda v: eq("nation_name", v))
    return [
        _single("P01", c, seg("BUILDING"), "name"),
        _single("P02", c, bal(8000), "name", "segment"),
        _single("P03", s, le("balance", 1000), "name"),
        _single("P04", p, eq("size", 15), "name", "price"),
        _single("P05", n, eq("region_name", "ASIA"), "name"),
        _single("P06", c, all_of(seg("MACHINERY"), bal(5000)), "name"),
        _single("P07", c, any_of(nat("NATION_2"), bal(9500)), "name", "nation_name"),
        _single("P08", p, all_of(eq("brand", "Brand#4"), le("size", 20)), "name", "type"),
        _single("P09", p, any_of(eq("type", "PROMO"), ge("size", 48)), "brand"),
        _single("P10", s, any_of(nat("NATION_9"), bal(9000)), "name", "balance"),
        _single("P11", p, all_of(eq("type", "SMALL"), ge("size", 30), le("price", 950)), "name"),
        _single("P12", p, any_of(eq("brand", "Brand#17"), eq("brand", "Brand#2"), eq("size", 2)), "name"),
        _single("P13", c, all_of(any_of(seg("BUILDING"), seg("FURNITURE")), bal(7000)), "name"),
        _single("P14", c, all_of(seg("HOUSEHOLD"), any_of(nat("NATION_1"), le("balance", 0))), "name", "balance"),
        _single("P15", p, any_of(all_of(eq("type", "LARGE"), le("size", 10)), all_of(eq("type", "ECONOMY"), ge("size", 45))), "name", "size", "price"),
        _single("P16", p, all_of(any_of(eq("brand", "Brand#8"), ge("size", 40)), any_of(ge("price", 950), all_of(eq("type", "MEDIUM"), le("size", 25)))), "name"),
        _single("P17", p, all_of(eq("type", "STANDARD"), ge("size", 10), le("size", 30), ge("price", 950)), "name", "brand"),
        _single("P18", c, all_of(between("balance", 1000, 2000), seg("AUTOMOBILE"), nat("NATION_7")), "name"),
        _single("P19", c, any_of(seg("AUTOMOBILE"), seg("MACHINERY"), le("balance", -500), nat("NATION_11")), "name"),
        _single("P20", "region", ge("n_customers", 300), "name", "n_nations"),
        Query("P21", (c, n), ((c, "name"), (n, "name")), {c: bal(9000), n: eq("region_name", "AFRICA")}, (_CN,)),
        Query("P22", (n, "region"), ((n, "name"),), {"region": eq("name", "EUROPE"), n: ge("n_customers", 50)}, (_NR,)),
        Query("P23", (n, s), ((n, "name"), (s, "name")), {s: bal(5000)}, (_NS,)),
        Query("P24", (c, n, "region"), ((c, "name"), (n, "name"), ("region", "name")), {c: all_of(seg("BUILDING"), bal(8000)), n: ge("n_customers", 60)}, (_CN, _NR)),
        Query("P25", (c, n, s, "region"), ((c, "name"), (n, "name"), (s, "name"), ("region", "name")), {c: bal(8500), s: bal(3000), "region": eq("name", "ASIA")}, (_CN, _NS, _NR)),
    ]


def suite_g() -> list[Query]:
    lang, tld, scheme = (lambda v: eq("html_lang", v)), (lambda v: eq("tld", v)), (lambda v: eq("scheme", v))
    q = lambda name, where, *select: _single(name, "page", where, *select)
    return [
        q("G01", lang("en"), "title"),
        q("G02", eq("path_lang", "fr"), "host"),
        q("G03", tld("org"), "title", "host"),
        q("G04", ge("path_no", 500), "scheme", "host", "path_lang", "path_no"),
        q("G05", all_of(scheme("https"), lang("en")), "title"),
        q("G06", any_of(eq("has_query", True), le("path_no", 100)), "host"),
        q("G07", all_of(ge("n_paragraphs", 8), lang("de")), "h1"),
        q("G08", all_of(le("nav_links", 6), tld("com"), scheme("http")), "site"),
        q("G09", any_of(eq("utm_source", "feed"), lang("es")), "title"),
        q("G10", all_of(any_of(tld("com"), tld("net")), ge("n_paragraphs", 5)), "site"),
        q("G11", all_of(le("track_id", 50), any_of(lang("en"), ge("path_no", 700))), "title"),
        q("G12", any_of(all_of(scheme("http"), tld("org")), all_of(scheme("https"), le("path_no", 300))), "host"),
        q("G13", all_of(lang("en"), scheme("https"), tld("com"), ge("path_no", 200)), "title", "host"),
        q("G14", any_of(lang("fr"), lang("de"), eq("utm_source", "feed"), ge("n_paragraphs", 20)), "site"),
        q("G15", all_of(any_of(lang("en"), lang("es")), any_of(tld("net"), all_of(scheme("https"), ge("n_paragraphs", 6)))), "title"),
    ]


def suite_c() -> list[Query]:
    from datetime import date

    status = lambda v: eq("status", v)
    q = lambda name, where, *select: _single(name, "order", where, *select)
    return [
        q("C01", status("F"), "order_key"),
        q("C02", ge("total_price", 400000), "customer_name"),
        q("C03", all_of(eq("priority", "1-URGENT"), ge("total_price", 200000)), "order_key"),
        q("C04", any_of(ge("n_lines", 5), ge("total_qty", 150)), "order_key", "n_lines"),
        q("C05", all_of(status("O"), eq("any_returned", True), ge("n_lines", 3)), "customer_name"),
        q("C06", between("order_date", date(1996, 1, 1), date(1997, 12, 31)), "order_key"),
        q("C07", all_of(any_of(status("F"), status("P")), le("total_price", 100000)), "order_key"),
        q("C08", any_of(eq("priority", "2-HIGH"), all_of(ge("total_qty", 120), le("n_lines", 4))), "order_key"),
        q("C09", all_of(status("P"), eq("priority", "5-LOW"), ge("total_price", 50000), ge("n_lines", 2)), "customer_name"),
        q("C10", all_of(any_of(status("O"), eq("any_returned", True)), any_of(ge("n_lines", 6), all_of(ge("total_price", 300000), eq("priority", "3-MEDIUM")))), "order_key"),
    ]


SUITES = {"P": suite_p, "G": suite_g, "C": suite_c}


def by_name(name: str) -> Query:
    return next(q for q in SUITES[name[0]]() if q.name == name)


def n_filters(q: Query) -> int:
    return sum(len(leaves(e)) for e in q.where.values())


def group(q: Query) -> str:
    """1 filter, 2 to 3, 4 or more."""
    n = n_filters(q)
    return "1" if n <= 1 else "2-3" if n <= 3 else "4+"


#: What the generator draws from; (attribute, constants), the same at every scale.
_DRAWS: dict[str, dict[str, Sequence]] = {
    "customer": {"segment": ("BUILDING", "FURNITURE", "MACHINERY", "HOUSEHOLD", "AUTOMOBILE"), "balance": (0, 1500, 3000, 4500, 6000, 7500), "nation_name": ("NATION_1", "NATION_5", "NATION_12", "NATION_20")},
    "nation": {"region_name": ("AFRICA", "AMERICA", "ASIA", "EUROPE"), "n_customers": (40, 55, 60, 70)},
    "region": {"n_customers": (200, 280, 300), "n_suppliers": (10, 18, 22)},
    "supplier": {"balance": (0, 2000, 4000, 6000, 8000), "nation_name": ("NATION_2", "NATION_9", "NATION_15")},
    "part": {"brand": ("Brand#1", "Brand#4", "Brand#8", "Brand#17"), "type": ("SMALL", "LARGE", "PROMO", "ECONOMY"), "size": (5, 15, 25, 35, 45), "price": (910, 930, 950, 970, 990)},
}


def _draw(seed: str, n: int) -> int:
    return int(hashlib.md5(seed.encode()).hexdigest()[:8], 16) % n


def random_filter(table: str, seed: str, filters: int) -> Expr:
    """A seeded conjunction, disjunction or mixed tree of so many filters over a table."""
    names = sorted(_DRAWS[table])
    made: list[Expr] = []
    for i in range(filters):
        name = names[_draw(f"{seed}:a{i}", len(names))]
        values = _DRAWS[table][name]
        value = values[_draw(f"{seed}:v{i}", len(values))]
        made.append(Leaf(name, "=" if isinstance(value, str) else ("<=", ">=")[_draw(f"{seed}:o{i}", 2)], (value,)))
    shape = _draw(f"{seed}:shape", 3)
    if filters < 3 or shape < 2:
        return (all_of, any_of)[shape % 2](*made) if filters > 1 else made[0]
    return all_of(any_of(*made[: filters // 2]), *made[filters // 2 :]) if filters > 2 else all_of(*made)


def make_queries(table: str, n: int, seed: str = "w", filters: Sequence[int] = (1, 2, 3, 4, 5)) -> list[Query]:
    """n seeded queries over a table, of numbers of filters in turn."""
    return [_single(f"{table}-{seed}-{i}", table, random_filter(table, f"{seed}:{table}:{i}", filters[i % len(filters)]), sorted(_DRAWS[table])[0]) for i in range(n)]


JOINS = {"customer-nation": _CN, "nation-region": _NR, "nation-supplier": _NS}


def make_joins(edges: Sequence[str], n: int, seed: str = "j", filters: Sequence[int] = (1, 2, 4)) -> list[Query]:
    """n seeded queries over the tables of some edges, filters dealt to the tables in turn."""
    chosen = [JOINS[e] for e in edges]
    tables = list(dict.fromkeys(t for e in chosen for t in (e.left, e.right)))
    made = []
    for i in range(n):
        k, where = filters[i % len(filters)], {}
        for j, t in enumerate(tables):
            own = k // len(tables) + (j < k % len(tables))
            if own:
                where[t] = random_filter(t, f"{seed}:{i}:{t}", own)
        made.append(Query(f"{'+'.join(edges)}-{i}", tuple(tables), tuple((t, "name") for t in tables), where, tuple(chosen)))
    return made


__all__ = ["SUITES", "by_name", "group", "isin", "make_joins", "make_queries", "n_filters", "suite_c", "suite_g", "suite_p"]
