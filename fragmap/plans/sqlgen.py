"""From mapped fragments and a join path to SQL text."""

from __future__ import annotations

from collections import Counter

from fragmap.operators.schema_graph import instance


def bag_of(frags: list[dict]) -> list[str]:
    """Known elements: attributes as often as predicates of one clause repeat them, relations of FROM mappings that no attribute covers."""
    counts: Counter[str] = Counter()
    for clause in {f["clause"] for f in frags} - {"FROM"}:
        own = Counter(f"{f['relation']}.{f['attribute']}" for f in frags if f["clause"] == clause)
        for key, n in own.items():
            counts[key] = max(counts[key], n if clause == "WHERE" else 1)
    covered = {k.split(".")[0] for k in counts}
    relations = {f["relation"] for f in frags if f["clause"] == "FROM"} - covered
    return sorted([*counts.elements(), *relations])


def instances_of(bag: list[str]) -> dict[str, list[str]]:
    """Relation instance of each reference of an attribute, numbered as forks are."""
    out, clone = {}, 0
    for entry, d in sorted(Counter(bag).items()):
        relation = entry.split(".")[0]
        out[entry] = [relation]
        for _ in range(d - 1):
            clone += 1
            out[entry].append(instance(relation, clone))
    return out


def _alias(inst: str) -> str:
    return inst.replace("#", "_")


def _column(f: dict, inst: str) -> str:
    text = f"{_alias(inst)}.{f['attribute']}"
    return f"{f['func']}({text})" if f["func"] else text


def literal(f: dict) -> str:
    if f.get("numeric"):
        return str(f["value"])
    return "'" + str(f["value"]).replace("'", "''") + "'"


def build_sql(frags: list[dict], vertices: list[str], edges: list[dict]) -> str:
    """Projections with their aggregates, relations in the order of the path, join conditions, predicates, grouping.

    Two aggregates make two levels: the first is computed per group, the second over groups.
    """
    where_of = instances_of(bag_of(frags))
    used: Counter[str] = Counter()
    select, groups, tests, levels = [], [], [], []
    for f in frags:
        if f["clause"] == "FROM":
            continue
        key = f"{f['relation']}.{f['attribute']}"
        if f["clause"] == "SELECT":
            text = _column(f, f["relation"])
            aggs = list(f["aggs"])
            if aggs:
                text = f"{aggs[0]}({text})"
                levels += aggs[1:]
            select.append(text)
            if not aggs:
                groups.append((text, bool(f.get("grouped"))))
        else:
            options = where_of.get(key, [f["relation"]])
            inst = options[min(used[key], len(options) - 1)]
            used[key] += 1
            tests.append(f"{_column(f, inst)} {f['op']} {literal(f)}")
    placed = [vertices[0]] if vertices else sorted({f["relation"] for f in frags})[:1]
    text = f"{placed[0].split('#')[0]} AS {_alias(placed[0])}"
    left = list(edges)
    while left:
        ready = next((e for e in left if {e["fk"].split(".")[0], e["pk"].split(".")[0]} & set(placed)), None)
        if ready is None:
            break
        left.remove(ready)
        ends = [ready["fk"].split("."), ready["pk"].split(".")]
        new = [r for r, _ in ends if r not in placed]
        on = " = ".join(f"{_alias(r)}.{c}" for r, c in ends)
        text += f" JOIN {new[0].split('#')[0]} AS {_alias(new[0])} ON {on}" if new else ""
        placed += new
    names = [f"{c} AS c{i}" for i, c in enumerate(select)] or ["*"]
    sql = f"SELECT {', '.join(names)} FROM {text}"
    if tests:
        sql += " WHERE " + " AND ".join(tests)
    if groups and (len(groups) < len(select) or any(g for _, g in groups)):
        sql += " GROUP BY " + ", ".join(c for c, _ in groups)
    for agg in levels:
        at = next(i for i, f in enumerate([f for f in frags if f["clause"] == "SELECT"]) if len(f["aggs"]) > 1)
        sql = f"SELECT {agg}(c{at}) AS c0 FROM ({sql}) AS per_group"
    return sql
