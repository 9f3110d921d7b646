"""The schema graph, its weights, its forks and its contraction to relations.

The graph is metadata: a few hundred vertices held by the driver and shipped to tasks
with the function that uses it.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fragmap.catalog import Catalog
from fragmap.operators.qfg import FragmentGraph

PROJECTION, KEY = "projection", "key"
PUBLISHED, CLOSURE = "published", "closure"


def instance(name: str, clone: int) -> str:
    """A vertex of clone ``clone``; the original is clone 0."""
    if not clone:
        return name
    relation, dot, attribute = name.partition(".")
    return f"{relation}#{clone}{dot}{attribute}"


def original(name: str) -> str:
    relation, dot, attribute = name.partition(".")
    return f"{relation.split('#')[0]}{dot}{attribute}"


@dataclass
class SchemaGraph:
    """``vertices`` are relation and relation.attribute names; ``edges`` (source, target, kind, edge id)."""

    vertices: list[str]
    edges: list[tuple[str, str, str, str]]
    weights: dict[str, float] = field(default_factory=dict)  # by edge id; clones use their original's

    def contracted(self) -> list[tuple[str, str, str, str, str, float]]:
        """(edge id, FK relation, PK relation, FK attribute, PK attribute, weight) per key edge; parallel keys stay apart."""
        return [(i, a.split(".")[0], b.split(".")[0], a, b, self.weights.get(i, 1.0)) for a, b, kind, i in self.edges if kind == KEY]

    def frames(self, spark: SparkSession) -> tuple[DataFrame, DataFrame]:
        v = [(x, "attribute" if "." in x else "relation", x.split(".")[0].split("#")[0], x.partition(".")[2] or None, int((x.split(".")[0].split("#") + ["0"])[1])) for x in self.vertices]
        e = [(a, b, kind, i or None, self.weights.get(i, 1.0)) for a, b, kind, i in self.edges]
        return (
            spark.createDataFrame(v, "vid string, kind string, relation string, attribute string, clone_no int"),
            spark.createDataFrame(e, "src string, dst string, kind string, edge_id string, w double"),
        )


def build_schema_graph(catalog: Catalog) -> SchemaGraph:
    vertices = list(catalog.relations) + [a.key for a in catalog.attributes]
    edges = [(a.relation, a.key, PROJECTION, "") for a in catalog.attributes]
    edges += [(f"{k.fk_relation}.{k.fk_attribute}", f"{k.pk_relation}.{k.pk_attribute}", KEY, k.edge_id) for k in catalog.keys]
    return SchemaGraph(vertices, edges)


def default_weights(graph: SchemaGraph) -> SchemaGraph:
    return SchemaGraph(graph.vertices, graph.edges, {})


def preset_weights(graph: SchemaGraph, table: dict[str, float]) -> SchemaGraph:
    """Hand-set weights by edge id; others stay 1."""
    return SchemaGraph(graph.vertices, graph.edges, dict(table))


def relation_dice(qfg: FragmentGraph) -> dict[tuple[str, str], float]:
    """Dice of relation pairs: as many rows as the schema has relations and joined pairs."""
    v = {r["expr"]: r["n_v"] for r in qfg.vertices.where("clause = 'FROM'").collect()}
    out = {}
    for r in qfg.edges.where("a_clause = 'FROM' and b_clause = 'FROM'").collect():
        total = v[r["a_expr"]] + v[r["b_expr"]]
        out[r["a_expr"], r["b_expr"]] = out[r["b_expr"], r["a_expr"]] = 2 * r["n_e"] / total
    return out


def weights_from_dice(graph: SchemaGraph, dice: dict[tuple[str, str], float]) -> SchemaGraph:
    weights = {}
    for a, b, kind, i in graph.edges:
        if kind == KEY:
            weights[i] = 1.0 - dice.get((original(a).split(".")[0], original(b).split(".")[0]), 0.0)
    return SchemaGraph(graph.vertices, graph.edges, weights)


def log_weights(graph: SchemaGraph, qfg: FragmentGraph) -> SchemaGraph:
    """1 - Dice of the two relations in the log."""
    return weights_from_dice(graph, relation_dice(qfg))


def fork(graph: SchemaGraph, attribute: str, clone: int, mode: str = PUBLISHED) -> SchemaGraph:
    """The graph with a copy of all that depends on ``attribute``'s relation.

    A copied foreign key whose target is not copied keeps pointing at the original.
    ``published`` walks with a stack, neighbours in ascending order, each marked when it is
    pushed; ``closure`` finds the copied set first and then draws every edge inside it.
    """
    base = [e for e in graph.edges if "#" not in e[0]]
    key_to: dict[str, list[str]] = {}
    near: dict[str, set[str]] = {}
    for a, b, kind, _ in base:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
        if kind == KEY:
            key_to.setdefault(a, []).append(b)
    marked, drawn, stack = {attribute}, set(), [attribute]
    while stack:
        at = stack.pop()
        for other in sorted(near.get(at, ())):
            if other in marked:
                continue
            if other in key_to.get(at, ()):
                drawn.add((at, other))  # to the original, unless it is copied in closure mode
                continue
            marked.add(other)
            drawn.add((at, other))
            stack.append(other)
    added = []
    for a, b, kind, i in base:
        if a not in marked:
            continue
        if mode == CLOSURE or kind == PROJECTION:
            target = instance(b, clone) if b in marked else b
        elif (b, a) in drawn:  # the copy of the key pulled this reference in
            target = instance(b, clone)
        else:
            target = b
        added.append((instance(a, clone), target, kind, i))
    return SchemaGraph(graph.vertices + [instance(v, clone) for v in graph.vertices if v in marked], graph.edges + added, graph.weights)


def fork_for_bag(graph: SchemaGraph, bag: list[str], catalog_keys: dict[str, str] | None = None, mode: str = PUBLISHED) -> tuple[SchemaGraph, list[str]]:
    """A graph with one copy for each further reference in ``bag``, and the terminal relations.

    Of an attribute given d times, d - 1 copies are made; a repeated relation is forked
    at its primary key.
    """
    terminals, clone = [], 0
    counts = Counter(bag)
    for entry, d in sorted(counts.items()):
        relation = entry.split(".")[0]
        if relation not in terminals:
            terminals.append(relation)
        start = entry if "." in entry else f"{relation}.{(catalog_keys or {}).get(relation, '')}"
        for _ in range(d - 1):
            if start not in graph.vertices:
                continue
            clone += 1
            graph = fork(graph, start, clone, mode)
            terminals.append(instance(relation, clone))
    return graph, terminals


def relations_of(bag: list[str]) -> list[str]:
    """Each attribute of a bag replaced by its relation; repeats stay."""
    return sorted(x.split(".")[0] for x in bag)
