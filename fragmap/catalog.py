"""Schema catalog: relations, attributes, keys and the words they are called by.

A catalog is metadata, so it lives in driver memory; its size follows the schema,
never the data.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

NUMERIC, TEXT, TEMPORAL, OTHER = "numeric", "text", "temporal", "other"


@dataclass(frozen=True)
class Attribute:
    relation: str
    name: str
    kind: str
    words: tuple[str, ...] = ()
    expr: str = ""  # SQL over the relation's row, where the attribute is derived

    @property
    def key(self) -> str:
        return f"{self.relation}.{self.name}"


@dataclass(frozen=True)
class ForeignKey:
    edge_id: str
    fk_relation: str
    fk_attribute: str
    pk_relation: str
    pk_attribute: str


@dataclass
class Catalog:
    name: str
    attributes: list[Attribute]
    keys: list[ForeignKey]
    words: dict[str, tuple[str, ...]] = field(default_factory=dict)

    @property
    def relations(self) -> list[str]:
        return list(dict.fromkeys(a.relation for a in self.attributes))

    def of(self, relation: str) -> list[Attribute]:
        return [a for a in self.attributes if a.relation == relation]

    def attribute(self, key: str) -> Attribute | None:
        return next((a for a in self.attributes if a.key == key), None)

    def resolve(self, column: str, relations: list[str]) -> str | None:
        """The relation of an unqualified column among those of a statement."""
        owners = [r for r in relations if any(a.name == column for a in self.of(r))]
        return owners[0] if len(owners) == 1 else None

    def primary_key(self, relation: str) -> str | None:
        return next((k.pk_attribute for k in self.keys if k.pk_relation == relation), None)

    def restrict(self, name: str, relations: list[str]) -> Catalog:
        return Catalog(
            name, [a for a in self.attributes if a.relation in relations],
            [k for k in self.keys if k.fk_relation in relations and k.pk_relation in relations],
            {r: w for r, w in self.words.items() if r in relations},
        )

    def frame(self, spark: SparkSession) -> DataFrame:
        rows = [(a.relation, a.name, a.kind, list(a.words), list(self.words.get(a.relation, ()))) for a in self.attributes]
        return spark.createDataFrame(rows, "relation string, attribute string, kind string, words array<string>, relation_words array<string>")

    def key_frame(self, spark: SparkSession) -> DataFrame:
        rows = [(k.edge_id, k.fk_relation, k.fk_attribute, k.pk_relation, k.pk_attribute) for k in self.keys]
        return spark.createDataFrame(rows, "edge_id string, fk_relation string, fk_attribute string, pk_relation string, pk_attribute string")


#: Relations, attributes, kinds and plain words of the given tables.
_TABLES = {
    "region": ("region", {"r_regionkey": (NUMERIC, "region key"), "r_name": (TEXT, "name")}),
    "nation": ("nation", {"n_nationkey": (NUMERIC, "nation key"), "n_name": (TEXT, "name"), "n_regionkey": (NUMERIC, "region key")}),
    "customer": ("customer", {
        "c_custkey": (NUMERIC, "customer key"), "c_name": (TEXT, "name"), "c_nationkey": (NUMERIC, "nation key"),
        "c_acctbal": (NUMERIC, "account balance"), "c_mktsegment": (TEXT, "market segment")}),
    "supplier": ("supplier", {
        "s_suppkey": (NUMERIC, "supplier key"), "s_name": (TEXT, "name"), "s_nationkey": (NUMERIC, "nation key"), "s_acctbal": (NUMERIC, "account balance")}),
    "part": ("part", {
        "p_partkey": (NUMERIC, "part key"), "p_name": (TEXT, "name"), "p_brand": (TEXT, "brand"), "p_type": (TEXT, "type"),
        "p_size": (NUMERIC, "size"), "p_retailprice": (NUMERIC, "retail price")}),
    "orders": ("order", {
        "o_orderkey": (NUMERIC, "order key"), "o_custkey": (NUMERIC, "customer key"), "o_orderstatus": (TEXT, "status"),
        "o_totalprice": (NUMERIC, "total price"), "o_orderdate": (TEMPORAL, "date"), "o_orderpriority": (TEXT, "priority")}),
    "lineitem": ("line item", {
        "l_orderkey": (NUMERIC, "order key"), "l_partkey": (NUMERIC, "part key"), "l_suppkey": (NUMERIC, "supplier key"),
        "l_linenumber": (NUMERIC, "line number"), "l_quantity": (NUMERIC, "quantity"), "l_extendedprice": (NUMERIC, "extended price"),
        "l_discount": (NUMERIC, "discount"), "l_tax": (NUMERIC, "tax"), "l_returnflag": (TEXT, "return flag"),
        "l_linestatus": (TEXT, "line status"), "l_shipdate": (TEMPORAL, "ship date")}),
    "events": ("event", {
        "event_id": (NUMERIC, "event id"), "ts": (TEMPORAL, "time"), "user_id": (NUMERIC, "user id"), "event_type": (TEXT, "event type"),
        "value": (NUMERIC, "value"), "props": (OTHER, "properties")}),
    "documents": ("document", {
        "doc_id": (NUMERIC, "document id"), "text": (TEXT, "text"), "lang": (TEXT, "language"), "source": (TEXT, "source"), "n_chars": (NUMERIC, "length characters")}),
    "labels": ("label", {"doc_id": (NUMERIC, "document id"), "quality": (NUMERIC, "quality"), "toxic": (NUMERIC, "toxic")}),
    "pages": ("page", {"page_id": (NUMERIC, "page id"), "url": (TEXT, "url address"), "html": (TEXT, "html")}),
    "benchmark": ("benchmark item", {"item_id": (NUMERIC, "item id"), "text": (TEXT, "text")}),
    "conversations": ("conversation", {"conv_id": (NUMERIC, "conversation id"), "turn": (NUMERIC, "turn"), "role": (TEXT, "role"), "text": (TEXT, "text message")}),
    "embeddings": ("embedding vector", {"vec_id": (NUMERIC, "vector id"), "embedding": (OTHER, "embedding"), "label": (NUMERIC, "label")}),
}
#: FK attribute -> PK attribute.
_KEYS = [
    ("F1", "nation", "n_regionkey", "region", "r_regionkey"), ("F2", "customer", "c_nationkey", "nation", "n_nationkey"),
    ("F3", "supplier", "s_nationkey", "nation", "n_nationkey"), ("F4", "orders", "o_custkey", "customer", "c_custkey"),
    ("F5", "lineitem", "l_orderkey", "orders", "o_orderkey"), ("F6", "lineitem", "l_partkey", "part", "p_partkey"),
    ("F7", "lineitem", "l_suppkey", "supplier", "s_suppkey"), ("F8", "events", "user_id", "customer", "c_custkey"),
    ("F9", "labels", "doc_id", "documents", "doc_id"),
]
BENCHMARKS = {
    "trade": ["region", "nation", "customer", "supplier", "part", "orders", "lineitem"],
    "activity": ["events", "customer", "nation", "region"],
    "corpus": ["documents", "labels", "pages", "benchmark", "conversations", "embeddings"],
    "all": list(_TABLES),
}


def given_catalog(benchmark: str = "all") -> Catalog:
    attributes, words = [], {}
    for relation, (called, columns) in _TABLES.items():
        words[relation] = tuple(called.split())
        attributes += [Attribute(relation, name, kind, tuple(text.split())) for name, (kind, text) in columns.items()]
    whole = Catalog("all", attributes, [ForeignKey(*k) for k in _KEYS], words)
    return whole if benchmark == "all" else whole.restrict(benchmark, BENCHMARKS[benchmark])


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def check_keys(spark: SparkSession, sf_dir: str, catalog: Catalog) -> DataFrame:
    """(edge_id, duplicates, orphans): repeated PK values and FK values without a match, both 0 if the keys hold."""
    out = None
    for k in catalog.keys:
        pk = table(spark, sf_dir, k.pk_relation).select(F.col(k.pk_attribute).alias("k"))
        fk = table(spark, sf_dir, k.fk_relation).select(F.col(k.fk_attribute).alias("k")).where("k is not null")
        repeated = pk.groupBy("k").count().where("count > 1").agg(F.count("*").alias("duplicates"))
        lost = fk.join(pk, "k", "left_anti").agg(F.count("*").alias("orphans"))
        row = repeated.join(lost, F.lit(True)).select(F.lit(k.edge_id).alias("edge_id"), "duplicates", "orphans")
        out = row if out is None else out.unionByName(row)
    return out
