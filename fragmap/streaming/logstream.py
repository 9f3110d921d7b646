"""The fragment graph over a stream of statements."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fragmap.catalog import Catalog
from fragmap.operators import fragments as fr
from fragmap.operators import qfg as qg
from fragmap.plans.lineage import shared_folder
from fragmap.sources import logs


def deduplicated(stream: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Statements once each; repeats later than the watermark are no longer recognised."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["log_id"])


def windowed_statements(stream: DataFrame, window: str = "1 day", slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """Statement templates per (tumbling or sliding) window; fragments follow from the templates."""
    masked = F.regexp_replace("sql", fr._LITERAL, "?").alias("template")
    span = F.window("ts", window, slide) if slide else F.window("ts", window)
    return stream.withWatermark("ts", delay).select("ts", masked).groupBy(span.alias("span"), "template").agg(F.count("*").alias("n"))


def session_counts(stream: DataFrame, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", delay).groupBy("user_id", F.session_window("ts", gap)).agg(F.count("*").alias("n"))


class GraphSink:
    """foreachBatch target: each micro-batch adds its counts as a table of its own, read back as one sum.

    Tables are named by batch id, so a batch that is run again replaces what it wrote.
    """

    def __init__(self, spark: SparkSession, path: str, catalog: Catalog, level: str = fr.NOCONSTOP):
        self.spark, self.path, self.catalog, self.level = spark, path.rstrip("/"), catalog, level

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        g = qg.build_qfg(batch, self.catalog, self.level)
        g.vertices.write.mode("overwrite").parquet(f"{self.path}/vertices/batch={batch_id}")
        g.edges.write.mode("overwrite").parquet(f"{self.path}/edges/batch={batch_id}")

    def graph(self) -> qg.FragmentGraph:
        v = self.spark.read.parquet(f"{self.path}/vertices").groupBy("clause", "expr").agg(F.sum("n_v").alias("n_v"))
        keys = ["a_clause", "a_expr", "b_clause", "b_expr"]
        return qg.FragmentGraph(v, self.spark.read.parquet(f"{self.path}/edges").groupBy(*keys).agg(F.sum("n_e").alias("n_e")), self.level)


def follow(stream: DataFrame, sink: GraphSink, checkpoint: str):
    """Runs over all that is there and stops; started again with the same checkpoint it goes on where it ended."""
    return stream.writeStream.foreachBatch(sink).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def count_stream(spark: SparkSession, sf_dir: str, catalog: Catalog, files: int = 4) -> DataFrame:
    """Writes the synthetic log as files, streams them in and returns the vertices of the resulting graph."""
    log = logs.synth_log(spark, sf_dir)
    work = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    log.repartition(files).write.parquet(f"{work}/log")
    sink = GraphSink(spark, f"{work}/graph", catalog)
    query = follow(logs.read_log_stream(spark, f"{work}/log", files_per_batch=1), sink, f"{work}/state")
    query.awaitTermination()
    return sink.graph().vertices
