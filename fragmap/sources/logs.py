"""Query logs: readers (batch and stream) and the synthetic log over ``events``.

A log is (log_id bigint, ts timestamp, user_id bigint, sql string).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fragmap.catalog import table

LOG_SCHEMA = "log_id bigint, ts timestamp, user_id bigint, sql string"


def read_log(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Parquet, JSON lines or CSV with the log's columns, or text with a statement per line."""
    if fmt == "text":
        lines = spark.read.text(path)
        return lines.select(
            F.xxhash64("value").alias("log_id"), F.lit(None).cast("timestamp").alias("ts"), F.lit(None).cast("bigint").alias("user_id"), F.col("value").alias("sql")
        )
    return spark.read.format(fmt).schema(LOG_SCHEMA).load(path)


def read_log_stream(spark: SparkSession, path: str, fmt: str = "parquet", files_per_batch: int | None = None) -> DataFrame:
    reader = spark.readStream.format(fmt).schema(LOG_SCHEMA)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    return reader.load(path)


#: SELECT list, relations with an instance number where repeated, key edges
#: (FK side, PK side), conditions (column, operator, value rule), tail. A relation's
#: instance is written relation or relation#2.
_NATION = ("nation.n_name", "=", "nation")
_SHOPPING = [("lineitem.l_partkey", "part.p_partkey"), ("lineitem.l_orderkey", "orders.o_orderkey"), ("orders.o_custkey", "customer.c_custkey"), ("customer.c_nationkey", "nation.n_nationkey")]
_T0 = (["part.p_name"], ["part", "lineitem", "orders", "customer", "nation"], _SHOPPING, [_NATION], "")
_T5 = (["supplier.s_name"], ["supplier"], [], [("supplier.s_acctbal", ">", "value")], "")
_T7 = (["orders.o_orderkey", "orders.o_totalprice"], ["orders", "customer"], [("orders.o_custkey", "customer.c_custkey")],
       [("customer.c_mktsegment", "=", "segment"), ("orders.o_totalprice", ">", "thousandfold")], "")
TEMPLATES = [
    _T0, _T0, _T0, _T0,
    (["part.p_name"], ["part", "lineitem", "supplier", "nation"],
     [("lineitem.l_partkey", "part.p_partkey"), ("lineitem.l_suppkey", "supplier.s_suppkey"), ("supplier.s_nationkey", "nation.n_nationkey")], [_NATION], ""),
    _T5, _T5, _T7, _T7,
    (["customer.c_name"], ["customer", "nation", "region"], [("customer.c_nationkey", "nation.n_nationkey"), ("nation.n_regionkey", "region.r_regionkey")], [("region.r_name", "=", "region")], ""),
    (["count(orders.o_orderkey)", "customer.c_mktsegment"], ["orders", "customer"], [("orders.o_custkey", "customer.c_custkey")], [], "GROUP BY customer.c_mktsegment"),
    (["sum(lineitem.l_extendedprice)", "part.p_brand"], ["lineitem", "part"], [("lineitem.l_partkey", "part.p_partkey")], [("part.p_type", "=", "'SMALL'")], "GROUP BY part.p_brand"),
    (["part.p_name"], ["part"], [], [("part.p_size", "<", "small")], "ORDER BY part.p_name"),
    (["orders.o_orderkey"], ["orders", "lineitem", "part", "lineitem#2", "part#2"],
     [("lineitem.l_orderkey", "orders.o_orderkey"), ("lineitem.l_partkey", "part.p_partkey"), ("lineitem#2.l_orderkey", "orders.o_orderkey"), ("lineitem#2.l_partkey", "part#2.p_partkey")],
     [("part.p_name", "=", "'red ring'"), ("part#2.p_name", "=", "'blue bolt'")], ""),
    (["supplier.s_name"], ["supplier", "lineitem", "orders", "customer"],
     [("lineitem.l_suppkey", "supplier.s_suppkey"), ("lineitem.l_orderkey", "orders.o_orderkey"), ("orders.o_custkey", "customer.c_custkey")], [("customer.c_name", "=", "customer")], ""),
    (["events.value"], ["events"], [], [("events.event_type", "=", "'purchase'"), ("events.value", ">", "value")], ""),
    (["customer.c_name"], ["customer", "events"], [("events.user_id", "customer.c_custkey")], [("events.event_type", "=", "'error'")], ""),
    (["avg(events.value)", "events.event_type"], ["events"], [], [], "GROUP BY events.event_type"),
    (["count(documents.doc_id)", "documents.lang"], ["documents"], [], [], "GROUP BY documents.lang"),
    (["documents.source"], ["documents", "labels"], [("labels.doc_id", "documents.doc_id")], [("labels.quality", "=", "1"), ("documents.n_chars", ">", "tenfold")], ""),
]
SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
REGIONS = ["AFRICA", "AMERICA", "ASIA", "EUROPE", "MIDDLE EAST"]


def _quoted(c: Column) -> Column:
    return F.concat(F.lit("'"), c, F.lit("'"))


def _values() -> dict[str, Column]:
    x, v = F.col("user_id"), F.col("value")
    k = F.get_json_object("props", "$.k").cast("bigint")
    pick = lambda names: F.element_at(F.array(*map(F.lit, names)), (x % 5 + 1).cast("int"))
    return {
        "nation": _quoted(F.concat(F.lit("NATION_"), (x % 25).cast("string"))), "value": v.cast("string"),
        "thousandfold": F.round(v * 1000).cast("bigint").cast("string"), "segment": _quoted(pick(SEGMENTS)), "region": _quoted(pick(REGIONS)),
        "small": (k % 50 + 1).cast("string"), "tenfold": (k * 10).cast("string"),
        "customer": _quoted(F.concat(F.lit("Customer#"), F.lpad(x.cast("string"), 9, "0"))),
    }


def _spelled(template: tuple, spelling: int) -> list[str]:
    """Text of a template with value rules as \\x01rule\\x01."""
    select, relations, joins, conditions, tail = template
    short: dict[str, str] = {}
    for i, r in enumerate(relations):
        base = r.split("#")[0]
        repeated = sum(q.split("#")[0] == base for q in relations) > 1
        short[r] = f"t{i}" if spelling or repeated else base
    word = (lambda w: w.lower()) if spelling == 1 else (lambda w: w)

    def named(text: str) -> str:
        inner = text[text.index("(") + 1 : -1] if "(" in text else text
        owner, column = inner.split(".")
        full = f"{short[owner]}.{column.upper() if spelling == 2 else column}"
        return text.replace(inner, full)

    def declared(r: str) -> str:
        base = r.split("#")[0]
        if short[r] == base:
            return base
        return f"{base} {'AS ' if spelling == 2 else ''}{short[r]}"

    tests = [f"{named(c)} {op} " + (rule if rule[0] in "'0123456789" else f"\x01{rule}\x01") for c, op, rule in conditions]
    links = [f"{named(a)} = {named(b)}" for a, b in joins]
    text = f"{word('SELECT')} {', '.join(map(named, select))} {word('FROM')} "
    if spelling == 2:
        seen, open_ = {relations[0]}, list(joins)
        text += declared(relations[0])
        for r in relations[1:]:
            seen.add(r)
            ready = [j for j in open_ if {x.split(".")[0] for x in j} <= seen]
            open_ = [j for j in open_ if j not in ready]
            text += f" JOIN {declared(r)} ON " + " AND ".join(f"{named(a)} = {named(b)}" for a, b in ready)
        where = tests
    else:
        text += ", ".join(map(declared, relations))
        where = links + tests if spelling == 0 else tests + links
    if where:
        text += f" {word('WHERE')} " + f" {word('AND')} ".join(where)
    if tail:
        head, _, column = tail.rpartition(" ")
        text += f" {word(head)} {named(column)}"
    return text.split("\x01")


def synth_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One statement per row of ``events``: template event_id % 20 in spelling event_id % 3."""
    rows = []
    for t, template in enumerate(TEMPLATES):
        for spelling in range(3):
            pieces = _spelled(template, spelling)
            rows.append((t, spelling, [(pieces[i], pieces[i + 1] if i + 1 < len(pieces) else "") for i in range(0, len(pieces), 2)]))
    texts = spark.createDataFrame(rows, "template int, spelling int, parts array<struct<text:string,rule:string>>")
    values = F.create_map(*[x for rule, c in {**_values(), "": F.lit("")}.items() for x in (F.lit(rule), c)])
    events = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "value", "props")
    events = events.withColumns({"template": (F.col("event_id") % 20).cast("int"), "spelling": (F.col("event_id") % 3).cast("int"), "values": values})
    sql = F.array_join(F.transform("parts", lambda p: F.concat(p["text"], F.element_at("values", p["rule"]))), "")
    spelled = events.join(F.broadcast(texts), ["template", "spelling"])  # 60 rows
    return spelled.select(F.col("event_id").alias("log_id"), F.col("ts").cast("timestamp").alias("ts"), "user_id", sql.alias("sql"))
