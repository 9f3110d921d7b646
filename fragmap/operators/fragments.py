"""From a log to fragments: fold statements to templates, parse templates, blur.

Folding is a native regexp and one partial aggregation, so Python reads each distinct
template once, however long the log is. Fragments carry three canonical keys, one per
level of obscurity; literals are attached again only where the level keeps them.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fragmap.catalog import Catalog
from fragmap.functions import sqltext

FULL, NOCONST, NOCONSTOP = "full", "noconst", "noconstop"
LEVELS = (FULL, NOCONST, NOCONSTOP)
CLAUSES = ("SELECT", "FROM", "WHERE")
#: a quoted text with doubled quotes, or a number that is no part of a name
_LITERAL = r"'(?:[^']|'')*'|(?<![A-Za-z_0-9#$.])[0-9]+(?:\.[0-9]+)?(?:[eE][+-]?[0-9]+)?(?![A-Za-z_0-9])"
FRAGMENT = (
    "clause string, relation string, attribute string, func string, aggs array<string>, op string, slots array<int>, expr string"
)


def fold_templates(log: DataFrame, keep_literals: bool = False, by: tuple[str, ...] = ()) -> DataFrame:
    """(template, [literals], by.., n): statements with equal text but for their literals."""
    masked = F.regexp_replace("sql", _LITERAL, "?").alias("template")
    cols = [*by, masked]
    if keep_literals:
        cols.append(F.regexp_extract_all("sql", F.lit(f"({_LITERAL})"), 1).alias("literals"))
    folded = log.where(F.col("sql").isNotNull()).select(*cols)
    return folded.groupBy(*folded.columns).agg(F.count("*").alias("n"))


def parse_templates(templates: DataFrame, catalog: Catalog, clauses: tuple[str, ...] = CLAUSES) -> DataFrame:
    """(template, error, frags): fragments of each distinct template; ``error`` says why one can't be read."""

    def read(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for text in batch["template"]:
                try:
                    found = [f for f in sqltext.fragments(text, catalog) if f.clause in clauses]
                    rows.append((text, None, [
                        {"clause": f.clause, "relation": f.relation, "attribute": f.attribute, "func": f.func, "aggs": list(f.aggs), "op": f.op, "slots": list(f.slots), "expr": f.expr}
                        for f in found
                    ]))
                except (sqltext.Unreadable, IndexError) as why:
                    rows.append((text, str(why), []))
            yield pd.DataFrame(rows, columns=["template", "error", "frags"])

    schema = f"template string, error string, frags array<struct<{FRAGMENT.replace(' ', ':').replace(',:', ',')}>>"
    return templates.select("template").distinct().mapInPandas(read, schema)


def key_of(frag: Column, level: str, literals: Column | None = None) -> Column:
    """Canonical text of a fragment at a level: clause, then expression, operator and value as far as kept."""
    expr, op = frag["expr"], frag["op"]
    if level == NOCONSTOP:
        tail = F.lit(" ?op ?val")
    elif level == NOCONST:
        tail = F.concat(F.lit(" "), op, F.lit(" ?val"))
    else:
        value = F.array_join(F.transform(frag["slots"], lambda s: F.get(literals, s)), ", ")
        tail = F.concat(F.lit(" "), op, F.lit(" "), value)
    return F.when(op == "", expr).otherwise(F.concat(expr, tail))


def keyed(frags: Column, level: str, literals: Column | None = None) -> Column:
    """array<struct<clause, expr>> of an array of fragments."""
    return F.transform(frags, lambda f: F.struct(f["clause"].alias("clause"), key_of(f, level, literals).alias("expr")))


def statement_fragments(
    log: DataFrame, catalog: Catalog, level: str = NOCONSTOP, clauses: tuple[str, ...] = CLAUSES, by: tuple[str, ...] = (), on_error: str = "skip"
) -> DataFrame:
    """(by.., n, keys): distinct kinds of statements with their number and their fragment keys, repeats kept."""
    folded = fold_templates(log, level == FULL, by)
    parsed = parse_templates(folded, catalog, clauses)
    if on_error == "fail":
        parsed = parsed.select("template", "frags", F.when(F.col("error").isNotNull(), F.raise_error(F.col("error"))).alias("error"))
    joined = folded.join(parsed, "template").where(F.col("error").isNull())
    return joined.select(*by, "n", keyed(F.col("frags"), level, F.col("literals") if level == FULL else None).alias("keys"))


def extract_fragments(log: DataFrame, catalog: Catalog, level: str = NOCONSTOP, clauses: tuple[str, ...] = CLAUSES) -> DataFrame:
    """(log_id, pos, clause, expr): every fragment of every statement."""
    masked = log.select("log_id", F.regexp_replace("sql", _LITERAL, "?").alias("template"), F.regexp_extract_all("sql", F.lit(f"({_LITERAL})"), 1).alias("literals"))
    parsed = parse_templates(masked, catalog, clauses).where(F.col("error").isNull())
    return (
        masked.join(parsed, "template")
        .select("log_id", F.posexplode(keyed(F.col("frags"), level, F.col("literals"))).alias("pos", "f")).select("log_id", "pos", "f.clause", "f.expr")
    )


def parse_errors(log: DataFrame, catalog: Catalog) -> DataFrame:
    """(template, error, n): statements that the reader leaves out."""
    folded = fold_templates(log)
    return folded.join(parse_templates(folded, catalog).where(F.col("error").isNotNull()), "template").select("template", "error", "n")
