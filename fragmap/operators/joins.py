"""Join inference: from bags of known elements to ranked join paths.

Distinct bags are few however many configurations there are; each is solved once in a
task that holds the schema graph and joined back by its key.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from fragmap.catalog import Catalog
from fragmap.operators import schema_graph as sg
from fragmap.operators import steiner
from fragmap.operators.qfg import FragmentGraph

RANKS = {
    "total_weight": (lambda: (F.col("total_w").asc(), F.col("n_edges").asc())),
    "published_desc": (lambda: (F.col("score").desc(), F.col("n_edges").asc())),
    "published_asc": (lambda: (F.col("score").asc(), F.col("n_edges").asc())),
    "support": (lambda: (F.col("support").desc(), F.col("n_edges").asc())),
}
_PATH = (
    "bag_key string, vertices array<string>, edges array<struct<edge_id:string,fk:string,pk:string,w:double>>, "
    "terminals array<string>, n_edges int, total_w double"
)


def path_score(total_w, n_edges):
    """Sum of weights over squared number of edges; a single relation has score 1."""
    return F.when(n_edges == 0, F.lit(1.0)).otherwise(total_w / (n_edges * n_edges))


def weighted_graph(catalog: Catalog, weights: str = "default", qfg: FragmentGraph | None = None, preset: dict[str, float] | None = None) -> sg.SchemaGraph:
    graph = sg.build_schema_graph(catalog)
    if weights == "log":
        return sg.log_weights(graph, qfg)
    if weights == "preset":
        return sg.preset_weights(graph, preset or {})
    return graph


def solve_bags(
    bags: DataFrame, catalog: Catalog, graph: sg.SchemaGraph, method: str = "exact", k_paths: int = 1, fork_mode: str = sg.PUBLISHED,
    ontology: dict[tuple[str, str], tuple[str, ...]] | None = None,
) -> DataFrame:
    """Paths of each distinct ``bag`` (sorted array<string> of relations and attributes), unranked."""
    keys = {r: catalog.primary_key(r) or "" for r in catalog.relations}

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for bag in batch["bag"]:
                rows += [("\x01".join(bag), *path) for path in paths_of(list(bag), graph, keys, method, k_paths, fork_mode, ontology)]
            yield pd.DataFrame(rows, columns=["bag_key", "vertices", "edges", "terminals", "n_edges", "total_w"])

    return bags.select("bag").distinct().mapInPandas(run, _PATH)


def paths_of(bag, graph, keys, method="exact", k_paths=1, fork_mode=sg.PUBLISHED, ontology=None) -> list[tuple]:
    forked, terminals = sg.fork_for_bag(graph, bag, keys, fork_mode)
    full = forked.contracted()
    # edge order decides how equal trees are listed
    full.sort(key=lambda e: (e[0], e[1], e[2]))
    edges = [(i, a, b, w) for i, a, b, _, _, w in full]
    if not terminals:
        return []
    if ontology is not None and len(set(terminals)) == 2:
        fixed = ontology.get(tuple(sorted(terminals)))
        trees = [frozenset(j for j, e in enumerate(edges) if e[0] in fixed and "#" not in e[1] + e[2])] if fixed else []
    else:
        trees = steiner.solve(edges, terminals, method, True, k_paths)
    out = []
    for tree in trees:
        own = [full[i] for i in sorted(tree)]
        vertices = sorted({v for e in own for v in e[1:3]} | set(terminals))
        out.append((
            vertices, [{"edge_id": e[0], "fk": e[3], "pk": e[4], "w": e[5]} for e in own], sorted(terminals), len(own), steiner.weight([edges[i] for i in tree])
        ))
    return out


def rank_paths(paths: DataFrame, rank_by: str = "total_weight") -> DataFrame:
    """Adds score, support, path_rank (ties broken by edge ids) and tied (another path is as good as the first)."""
    scored = paths.withColumns({
        "score": path_score(F.col("total_w"), F.col("n_edges")),
        "support": F.when(F.col("n_edges") == 0, 1.0).otherwise((F.col("n_edges") - F.col("total_w")) / (F.col("n_edges") * F.col("n_edges"))),
        "total_w": F.round("total_w", 12),
    })
    order = RANKS[rank_by]()
    by = Window.partitionBy("bag_key").orderBy(*order, F.concat_ws(",", "edges.edge_id", "edges.fk"))
    place = F.rank().over(Window.partitionBy("bag_key").orderBy(*order))
    ranked = scored.withColumns({"path_rank": F.row_number().over(by), "_place": place})
    firsts = F.sum(F.when(F.col("_place") == 1, 1).otherwise(0)).over(Window.partitionBy("bag_key"))
    return ranked.withColumn("tied", firsts > 1).drop("_place")


def infer_joins(
    bags: DataFrame, catalog: Catalog, qfg: FragmentGraph | None = None, weights: str = "log", k_paths: int = 1, rank_by: str = "total_weight",
    method: str = "exact", preset: dict[str, float] | None = None, fork_mode: str = sg.PUBLISHED, graph: sg.SchemaGraph | None = None,
) -> DataFrame:
    """``bags`` (bag_id, bag array<string>) with their ranked join paths; a bag that no tree joins has none."""
    graph = graph or weighted_graph(catalog, weights, qfg, preset)
    keyed = bags.select("bag_id", F.array_sort("bag").alias("bag"))
    paths = rank_paths(solve_bags(keyed, catalog, graph, method, k_paths, fork_mode), rank_by)
    return keyed.withColumn("bag_key", F.array_join("bag", "\x01")).join(paths, "bag_key").drop("bag_key")
