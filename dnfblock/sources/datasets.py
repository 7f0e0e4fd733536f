"""The seven dataset pairs, derived from the given tables by rules on keys.

A side is one SELECT that Spark and DuckDB both run; ``{customer}`` and so on stand for tables. A
column ``f`` gives field f; ``f__2`` is a second value of f and ``f__all`` an array of values. Fields
are sets of strings: a null adds nothing.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

MONEY = "cast(cast(round({0}) as bigint) as string)"
CENTS = "cast(cast(round({0} * 100) as bigint) as string)"
DAY = "cast(year({0}) as string) || '-' || lpad(cast(month({0}) as string), 2, '0') || '-' || lpad(cast(day({0}) as string), 2, '0')"
LEFT, RIGHT = "'urn:l:' || md5(cast({0} as string))", "'urn:r:' || md5('x' || cast({0} as string))"


def _money(x: str) -> str:
    return MONEY.format(x)


@dataclass(frozen=True)
class Side:
    sql: str
    fields: tuple[str, ...]
    kind: str  # "rdf" or "table"


@dataclass(frozen=True)
class Pair:
    name: str
    left: Side
    right: Side
    truth_sql: str
    mappings: tuple[tuple[tuple[str, ...], tuple[str, ...]], ...]


P1 = Pair(
    "p1",
    Side(
        f"""select {LEFT.format('c_custkey')} as rid, c_name as fullName, c_mktsegment as segment,
        {_money('c_acctbal')} as balance, n_name as nationName
        from {{customer}} join {{nation}} on c_nationkey = n_nationkey where c_custkey % 5 = 0""",
        ("fullName", "segment", "balance", "nationName"),
        "rdf",
    ),
    Side(
        f"""select {RIGHT.format('c_custkey')} as rid,
        case when c_custkey % 7 = 0 then null when c_custkey % 4 = 1 then 'Cust No ' || split_part(c_name, '#', 2) else c_name end as label,
        case when c_custkey % 11 = 0 then 'alias ' || split_part(c_name, '#', 2) end as label__2,
        lower(c_mktsegment) as marketArea,
        {_money('c_acctbal + case when c_custkey % 9 = 0 then 1 else 0 end')} as funds,
        case when c_custkey % 13 <> 0 then n_name end as homeCountry
        from {{customer}} join {{nation}} on c_nationkey = n_nationkey where c_custkey % 3 <> 1""",
        ("label", "marketArea", "funds", "homeCountry"),
        "rdf",
    ),
    f"""select {LEFT.format('c_custkey')} as l_rid, {RIGHT.format('c_custkey')} as r_rid from {{customer}}
    where c_custkey % 5 = 0 and c_custkey % 3 <> 1""",
    ((("fullName",), ("label",)), (("segment",), ("marketArea",)), (("balance",), ("funds",)), (("nationName",), ("homeCountry",))),
)
P2 = Pair(
    "p2",
    Side(
        f"""select {LEFT.format('o_orderkey')} as rid, c_name as buyer, {DAY.format('o_orderdate')} as placedOn,
        {_money('o_totalprice')} as price, o_orderstatus as state, o_orderpriority as priority
        from {{orders}} join {{customer}} on o_custkey = c_custkey where o_orderkey % 10 < 4""",
        ("buyer", "placedOn", "price", "state", "priority"),
        "rdf",
    ),
    Side(
        f"""select {RIGHT.format('o_orderkey')} as rid, split_part(c_name, '#', 1) as buyerKind, split_part(c_name, '#', 2) as buyerNo,
        cast(year(o_orderdate) as string) as year, lpad(cast(month(o_orderdate) as string), 2, '0') as month,
        lpad(cast(day(o_orderdate) as string), 2, '0') as day,
        {_money('o_totalprice + case when o_orderkey % 9 = 0 then 1 else 0 end')} as total, o_orderstatus as status,
        split_part(o_orderpriority, '-', 1) as rank, split_part(o_orderpriority, '-', 2) as urgency
        from {{orders}} join {{customer}} on o_custkey = c_custkey where o_orderkey % 10 >= 2 and o_orderkey % 10 <= 5""",
        ("buyerKind", "buyerNo", "year", "month", "day", "total", "status", "rank", "urgency"),
        "rdf",
    ),
    f"""select {LEFT.format('o_orderkey')} as l_rid, {RIGHT.format('o_orderkey')} as r_rid from {{orders}}
    where o_orderkey % 10 in (2, 3)""",
    (
        (("buyer",), ("buyerKind", "buyerNo")), (("placedOn",), ("year", "month", "day")), (("price",), ("total",)),
        (("state",), ("status",)), (("priority",), ("rank", "urgency")),
    ),
)
_LINE = "cast(l_orderkey as string) || '.' || cast(l_linenumber as string) || '.' || cast(l_partkey as string) || '.' || cast(l_suppkey as string)"
_ONCE = "(select *, count(*) over (partition by l_orderkey, l_linenumber, l_partkey, l_suppkey) as copies from {lineitem}) as u"
P3 = Pair(
    "p3",
    Side(
        f"""select {LEFT.format(_LINE)} as rid, cast(l_orderkey as string) as orderkey, cast(l_partkey as string) as partkey,
        cast(l_suppkey as string) as suppkey, cast(l_linenumber as string) as linenumber, {_money('l_quantity')} as quantity,
        {CENTS.format('l_extendedprice')} as extendedprice, {CENTS.format('l_discount')} as discount, {CENTS.format('l_tax')} as tax,
        l_returnflag as returnflag, l_linestatus as linestatus, {DAY.format('l_shipdate')} as shipdate
        from {_ONCE} where copies = 1 and l_orderkey % 20 = 0""",
        ("orderkey", "partkey", "suppkey", "linenumber", "quantity", "extendedprice", "discount", "tax", "returnflag", "linestatus", "shipdate"),
        "table",
    ),
    Side(
        f"""select {RIGHT.format(_LINE)} as rid, cast(l_orderkey as string) as order_no, cast(l_partkey as string) as part_no,
        case when l_partkey % 7 <> 0 then cast(l_suppkey as string) end as vendor_no, cast(l_linenumber as string) as line_no,
        {_money('l_quantity')} as qty, {_money('l_extendedprice')} as amount, {CENTS.format('l_discount')} as rebate_pct,
        l_returnflag as flag, l_linestatus as line_state, {DAY.format('l_shipdate')} as shipped
        from {_ONCE} where copies = 1 and l_orderkey % 10 in (0, 5) and l_partkey % 3 <> 0""",
        ("order_no", "part_no", "vendor_no", "line_no", "qty", "amount", "rebate_pct", "flag", "line_state", "shipped"),
        "table",
    ),
    f"""select {LEFT.format(_LINE)} as l_rid, {RIGHT.format(_LINE)} as r_rid from {_ONCE}
    where copies = 1 and l_orderkey % 20 = 0 and l_partkey % 3 <> 0""",
    tuple(
        ((a,), (b,))
        for a, b in (
            ("orderkey", "order_no"), ("partkey", "part_no"), ("suppkey", "vendor_no"), ("linenumber", "line_no"), ("quantity", "qty"),
            ("extendedprice", "amount"), ("discount", "rebate_pct"), ("returnflag", "flag"), ("linestatus", "line_state"), ("shipdate", "shipped"),
        )
    ),
)
P4 = Pair(
    "p4",
    Side(
        f"""select {LEFT.format('o_orderkey')} as rid, o_orderstatus as status, cast(o_custkey as string) as customer_no,
        {_money('o_totalprice')} as total, {DAY.format('o_orderdate')} as ordered, o_orderpriority as prio
        from {{orders}} where o_orderkey % 3 <> 0""",
        ("status", "customer_no", "total", "ordered", "prio"),
        "table",
    ),
    Side(
        f"""select {RIGHT.format('o_orderkey')} as rid, cast(year(o_orderdate) as string) as year,
        lpad(cast(month(o_orderdate) as string), 2, '0') as month, lpad(cast(day(o_orderdate) as string), 2, '0') as day,
        {_money('o_totalprice + case when o_orderkey % 7 = 0 then 1 else 0 end')} as total, o_orderstatus as status,
        split_part(o_orderpriority, '-', 1) as rank, split_part(o_orderpriority, '-', 2) as urgency,
        c_name as customer_label, c_mktsegment as segment, n_name as country
        from {{orders}} join {{customer}} on o_custkey = c_custkey join {{nation}} on c_nationkey = n_nationkey
        where o_orderkey % 4 <> 0""",
        ("year", "month", "day", "total", "status", "rank", "urgency", "customer_label", "segment", "country"),
        "table",
    ),
    f"""select {LEFT.format('o_orderkey')} as l_rid, {RIGHT.format('o_orderkey')} as r_rid from {{orders}}
    where o_orderkey % 3 <> 0 and o_orderkey % 4 <> 0""",
    (
        (("ordered",), ("year", "month", "day")), (("prio",), ("rank", "urgency")), (("customer_no",), ("customer_label",)),
        (("total",), ("total",)), (("status",), ("status",)),
    ),
)
P5 = Pair(
    "p5",
    Side(
        f"""select {LEFT.format('p_partkey')} as rid, p_name, p_brand, p_type, cast(p_size as string) as p_size,
        {_money('p_retailprice')} as p_retailprice from {{part}} where p_partkey % 2 = 0""",
        ("p_name", "p_brand", "p_type", "p_size", "p_retailprice"),
        "table",
    ),
    Side(
        f"""select {RIGHT.format('p_partkey')} as rid,
        case when p_name like '% % %' then p_name when p_name like '% %' then split_part(p_name, ' ', 2) || ' ' || split_part(p_name, ' ', 1) else p_name end as hasTitle,
        'Maker ' || regexp_extract(p_brand, '[0-9]+', 0) as hasMaker,
        case when p_partkey % 16 <> 2 then {_money('p_retailprice')} end as hasCost from {{part}} where p_partkey % 3 <> 0""",
        ("hasTitle", "hasMaker", "hasCost"),
        "rdf",
    ),
    f"""select {LEFT.format('p_partkey')} as l_rid, {RIGHT.format('p_partkey')} as r_rid from {{part}}
    where p_partkey % 2 = 0 and p_partkey % 3 <> 0""",
    ((("p_name",), ("hasTitle",)), (("p_brand",), ("hasMaker",)), (("p_retailprice",), ("hasCost",))),
)
_SECOND = DAY.format("ts") + " || ' ' || lpad(cast(hour(ts) as string), 2, '0') || ':' || lpad(cast(minute(ts) as string), 2, '0') || ':' || lpad(cast(cast(floor(second(ts)) as int) as string), 2, '0')"
P6 = Pair(
    "p6",
    Side(
        f"""select {LEFT.format('event_id')} as rid, cast(user_id as string) as user_id, event_type, {CENTS.format('value')} as value,
        {_SECOND} as ts, regexp_extract(props, '"k": *"?([A-Za-z0-9_.-]*)', 1) as k from {{events}} where event_id % 2 = 0""",
        ("user_id", "event_type", "value", "ts", "k"),
        "table",
    ),
    Side(
        f"""select {RIGHT.format('event_id')} as rid, cast(user_id as string) as actor, upper(event_type) as kind,
        case when event_id % 10 <> 4 then {CENTS.format('value')} end as amount from {{events}} where event_id % 3 <> 0""",
        ("actor", "kind", "amount"),
        "rdf",
    ),
    f"""select {LEFT.format('event_id')} as l_rid, {RIGHT.format('event_id')} as r_rid from {{events}}
    where event_id % 2 = 0 and event_id % 3 <> 0""",
    ((("user_id",), ("actor",)), (("event_type",), ("kind",)), (("value",), ("amount",))),
)
P7 = Pair(
    "p7",
    Side(
        f"""select {LEFT.format('page_id')} as rid, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) as host,
        regexp_extract(url, '^[a-z]+://[^/?#]*([^?#]*)', 1) as path, regexp_extract(html, '<title>([^<]*)</title>', 1) as title
        from {{pages}} where page_id % 4 <> 3""",
        ("host", "path", "title"),
        "table",
    ),
    Side(
        f"""select {RIGHT.format('page_id')} as rid, regexp_extract(html, '<html lang="([^"]*)"', 1) as lang,
        case when page_id % 6 = 1 then substr(lower(regexp_extract(html, '<h1>([^<]*)</h1>', 1)), 1, 20)
        else lower(regexp_extract(html, '<h1>([^<]*)</h1>', 1)) end as heading,
        regexp_extract_all(html, 'href="([^"]*)"', 1) as link__all,
        case when page_id % 9 <> 0 then regexp_extract(html, '<title>([^<]*)</title>', 1) end as titleText
        from {{pages}} where page_id % 4 <> 2""",
        ("lang", "heading", "link", "titleText"),
        "rdf",
    ),
    f"""select {LEFT.format('page_id')} as l_rid, {RIGHT.format('page_id')} as r_rid from {{pages}}
    where page_id % 4 <> 3 and page_id % 4 <> 2""",
    ((("title",), ("titleText", "heading")), (("path",), ("lang",))),
)
PAIRS = {p.name: p for p in (P1, P2, P3, P4, P5, P6, P7)}


def run_sql(spark: SparkSession, sf_dir: str, sql: str) -> DataFrame:
    """Run a SELECT with table placeholders on the Parquet tables below ``sf_dir``."""
    names = sorted(set(re.findall(r"\{([a-z]+)\}", sql)))
    tables = {n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in names}
    return spark.sql(sql, **tables)


def _columns(sql_columns: list[str], field: str) -> list[str]:
    return [c for c in sql_columns if c == field or c.startswith(f"{field}__")]


def side(spark: SparkSession, sf_dir: str, which: Side, fields: tuple[str, ...] | None = None) -> DataFrame:
    """``rid`` and one ``array<string>`` per field, empty where there is no value; other fields are pruned."""
    rows = run_sql(spark, sf_dir, which.sql)
    out = []
    for f in fields or which.fields:
        cols = _columns(rows.columns, f)
        single = [F.col(c) for c in cols if not c.endswith("__all")]
        values = F.col(cols[0]) if not single else F.array(*single)
        out.append(F.array_distinct(F.filter(values, lambda x: x.isNotNull())).alias(f))
    return rows.select("rid", *out)


def truth(spark: SparkSession, sf_dir: str, pair: Pair) -> DataFrame:
    """``l_rid, r_rid`` of the matching records."""
    return run_sql(spark, sf_dir, pair.truth_sql)


def load(spark: SparkSession, sf_dir: str, pair: Pair) -> tuple[DataFrame, DataFrame, DataFrame]:
    return side(spark, sf_dir, pair.left), side(spark, sf_dir, pair.right), truth(spark, sf_dir, pair)


def duck(sql: str) -> str:
    """``sql`` with the placeholders as plain table names."""
    return re.sub(r"\{([a-z]+)\}", r"\1", sql)


def duck_side(which: Side) -> str:
    """The same side as DuckDB SQL with list columns."""
    text = duck(which.sql)
    cols = []
    for f in which.fields:
        if f"as {f}__all" in text:
            cols.append(f'list_distinct({f}__all) AS "{f}"')
        elif f"as {f}__2" in text:
            cols.append(f'list_filter([{f}, {f}__2], lambda x: x IS NOT NULL) AS "{f}"')
        else:
            cols.append(f'list_filter([{f}], lambda x: x IS NOT NULL) AS "{f}"')
    return f"SELECT rid, {', '.join(cols)} FROM ({text}) AS s"
