"""Plain synonyms, written before any accuracy was measured."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fragmap.functions.stem import porter_stem

#: Word, synonym, closeness.
SYNONYMS = [
    ("item", "part", 0.8), ("product", "part", 0.8), ("article", "part", 0.5), ("component", "part", 0.7), ("vendor", "supplier", 0.9), ("seller", "supplier", 0.8),
    ("client", "customer", 0.9), ("buyer", "customer", 0.8), ("user", "customer", 0.6), ("visitor", "customer", 0.6), ("country", "nation", 0.9), ("area", "region", 0.7),
    ("purchase", "order", 0.7), ("sale", "order", 0.6), ("cost", "price", 0.8), ("revenue", "price", 0.7), ("amount", "value", 0.8), ("amount", "quantity", 0.8), ("sum", "total", 0.7),
    ("money", "balance", 0.6), ("big", "size", 0.5), ("length", "size", 0.6), ("after", "date", 0.6), ("since", "date", 0.6), ("year", "date", 0.7), ("action", "event", 0.8), ("activity", "event", 0.8),
    ("kind", "type", 0.8), ("sort", "type", 0.6), ("mean", "average", 0.9), ("article", "document", 0.8), ("text", "document", 0.6), ("message", "text", 0.7), ("address", "url", 0.8),
    ("site", "page", 0.7), ("tongue", "language", 0.8), ("origin", "source", 0.8), ("longer", "length", 0.8), ("long", "length", 0.8), ("good", "quality", 0.6), ("bad", "toxic", 0.5),
    ("cheaper", "price", 0.7), ("cheap", "price", 0.7), ("worth", "value", 0.7), ("score", "value", 0.5), ("line", "item", 0.5), ("shipped", "ship", 1.0), ("title", "name", 0.7), ("called", "name", 0.6),
    ("group", "segment", 0.6), ("urgency", "priority", 0.8), ("rebate", "discount", 0.8), ("vector", "embedding", 0.9), ("speaker", "role", 0.7), ("talk", "conversation", 0.8),
]


def glossary(spark: SparkSession) -> DataFrame:
    rows = [(porter_stem(a), porter_stem(b), s) for a, b, s in SYNONYMS]
    return spark.createDataFrame(rows, "word string, synonym string, score double").groupBy("word", "synonym").agg(F.max("score").alias("score"))
