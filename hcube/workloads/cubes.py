"""Cubes over the given tables."""

from __future__ import annotations

from ..spec import Cube, Dimension


def _text(e: str) -> str:
    return f"CAST({e} AS STRING)"


def _cents(e: str) -> str:
    return f"CAST(ROUND({e} * 100) AS BIGINT)"


def _month(c: str) -> str:
    return f"({_text(f'year({c})')} || '-' || lpad({_text(f'month({c})')}, 2, '0'))"


def _day(c: str) -> str:
    return _text(f"CAST({c} AS DATE)")


def _tens(c: str, n: int) -> str:
    return _text(f"CAST(floor({c} / {n}) AS BIGINT)")


C1 = Cube(
    "c1",
    "{lineitem} l JOIN {supplier} s ON l.l_suppkey = s.s_suppkey JOIN {nation} n ON s.s_nationkey = n.n_nationkey "
    "JOIN {region} r ON n.n_regionkey = r.r_regionkey JOIN {part} p ON l.l_partkey = p.p_partkey",
    (
        Dimension("geo", (("region", "r_name"), ("nation", "n_name"), ("supplier", _text("s_suppkey")))),
        Dimension("product", (("type", "p_type"), ("brand", "(p_type || '/' || p_brand)"), ("part", _text("p_partkey")))),
        Dimension("time", (("year", _text("year(l_shipdate)")), ("month", _month("l_shipdate")), ("day", _day("l_shipdate")))),
    ),
    (("qty", "CAST(l_quantity AS BIGINT)"), ("cents", _cents("l_extendedprice"))),
    ("lineitem", "supplier", "nation", "region", "part"),
)

_CUSTOMER_GEO = (("region", "r_name"), ("nation", "n_name"), ("customer", _text("c_custkey")))
_ORDER_TIME = (
    ("year", _text("year(o_orderdate)")),
    ("quarter", f"({_text('year(o_orderdate)')} || '-Q' || {_text('quarter(o_orderdate)')})"),
    ("month", _month("o_orderdate")), ("day", _day("o_orderdate")),
)
C2 = Cube(
    "c2",
    "{orders} o JOIN {customer} c ON o.o_custkey = c.c_custkey JOIN {nation} n ON c.c_nationkey = n.n_nationkey "
    "JOIN {region} r ON n.n_regionkey = r.r_regionkey",
    (Dimension("geo", _CUSTOMER_GEO, ("region", "nation", "nation", "customer")), Dimension("time", _ORDER_TIME)),
    (("cents", _cents("o_totalprice")),),
    ("orders", "customer", "nation", "region"),
)
C2_ABOVE = C2.with_plan(geo=("region", "region", "nation", "customer"))

C3 = Cube(
    "c3", "{lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey",
    (
        Dimension("flag", (("flag", "l_returnflag"), ("line", "(l_returnflag || '/' || l_linestatus)"))),
        Dimension("state", (("state", "o_orderstatus"), ("priority", "(o_orderstatus || '/' || o_orderpriority)"))),
    ),
    (("qty", "CAST(l_quantity AS BIGINT)"), ("discount", _cents("l_discount"))),
    ("lineitem", "orders"),
)

#: JSON is read by a pattern so that Spark and DuckDB share the text.
_K = "CAST(regexp_extract(props, '\"k\": *([0-9]+)', 1) AS BIGINT)"
C4 = Cube(
    "c4", "{events} e",
    (
        Dimension("user", (("hundred", _tens("user_id", 100)), ("ten", _tens("user_id", 10)), ("user", _text("user_id")))),
        Dimension("type", (("type", "event_type"), ("tens", f"(event_type || '/' || {_tens(_K, 10)})"), ("k", f"(event_type || '/' || {_tens(_K, 10)} || '/' || {_text(_K)})"))),
        Dimension("time", (("month", _month("ts")), ("day", _day("ts")), ("hour", f"({_day('ts')} || 'T' || lpad({_text('hour(ts)')}, 2, '0'))"))),
    ),
    (("cents", _cents("value")),), ("events",),
)

#: The same properties read as JSON; DuckDB's name of the function is ``JSON_IN_DUCKDB``.
JSON_IN_SPARK, JSON_IN_DUCKDB = "get_json_object", "json_extract_string"
_J = f"CAST({JSON_IN_SPARK}(props, '$.k') AS BIGINT)"
C4_JSON = Cube(
    "c4_json", "{events} e",
    (
        Dimension("props", (("tens", _tens(_J, 10)), ("k", f"({_tens(_J, 10)} || '/' || {_text(_J)})"))),
        Dimension("type", (("type", "event_type"),), ("type", "type")),
    ),
    (("cents", _cents("value")),), ("events",),
)

C5 = Cube(
    "c5", "{documents} d LEFT JOIN {labels} b ON d.doc_id = b.doc_id",
    (
        Dimension("place", (("lang", "lang"), ("source", "(lang || '/' || source)"), ("doc", _text("d.doc_id")))),
        Dimension("size", (("digits", _text("length(CAST(n_chars AS STRING))")),), ("digits", "digits", "digits")),
    ),
    (("chars", "CAST(n_chars AS BIGINT)"), ("quality", "CAST(coalesce(quality, 0) AS BIGINT)"), ("toxic", "CAST(coalesce(toxic, 0) AS BIGINT)")),
    ("documents", "labels"),
)

_HOST = "regexp_extract(url, '^[a-z]+://([^/?#]*)', 1)"
C6 = Cube(
    "c6", "{pages} p",
    (
        Dimension("host", (("tld", f"regexp_extract({_HOST}, '([^.]*)$', 1)"), ("domain", f"regexp_extract({_HOST}, '([^.]*[.][^.]*[.][^.]*)$', 1)"), ("host", _HOST))),
        Dimension("section", (("section", "regexp_extract(url, '^[a-z]+://[^/]*/([^/?#]*)', 1)"),), ("section",) * 3),
    ),
    (("chars", "CAST(length(html) AS BIGINT)"),), ("pages",),
)

C7 = Cube(
    "c7", "{conversations} c",
    (
        Dimension("talk", (("ten", _tens("conv_id", 10)), ("talk", _text("conv_id"))), ("ten", "talk", "talk")),
        Dimension("speech", (("role", "role"), ("turn", f"(role || '/' || {_text('turn')})")), ("role", "role", "turn")),
    ),
    (("chars", "CAST(length(text) AS BIGINT)"),), ("conversations",),
)

C9 = Cube(
    "c9", "{benchmark} b",
    (
        Dimension("item", (("ten", _tens("item_id", 10)), ("item", _text("item_id")))),
        Dimension("size", (("hundred", _tens("length(text)", 100)), ("length", _text("length(text)")))),
    ),
    (("chars", "CAST(length(text) AS BIGINT)"),), ("benchmark",),
)


def _balance(table: str, prefix: str) -> Cube:
    return Cube(
        f"s_{table}", f"{{{table}}} t JOIN {{nation}} n ON t.{prefix}_nationkey = n.n_nationkey JOIN {{region}} r ON n.n_regionkey = r.r_regionkey",
        (Dimension("geo", (("region", "r_name"), ("nation", "n_name"), ("one", _text(f"{prefix}_{'suppkey' if prefix == 's' else 'custkey'}")))),),
        (("cents", _cents(f"{prefix}_acctbal")),), (table, "nation", "region"),
    )


S_SUPPLIER, S_CUSTOMER = _balance("supplier", "s"), _balance("customer", "c")
ALL = {c.name: c for c in (C1, C2, C3, C4, C4_JSON, C5, C6, C7, C9, S_SUPPLIER, S_CUSTOMER)}
