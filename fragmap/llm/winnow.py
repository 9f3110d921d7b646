"""Document fingerprints by winnowing. DataFrame functions only.

Units are runs of at most ``UNIT_CHARS`` characters without white space, and the single
characters of longer runs, so that units do not depend on where a run begins. Hashes of
``GRAM`` consecutive units are taken at every position; of each ``WINDOW``
consecutive hashes the least is selected, the rightmost of equal ones, with its
position. Two texts sharing ``GRAM + WINDOW - 1`` consecutive units therefore share
a selected hash. A hash and its position travel as one long, so that one minimum
settles both value and tie.

Defined cases: a null or empty text, or white space alone, selects nothing; a text of
fewer than ``GRAM`` units has one hash over all of them, fewer than ``WINDOW`` hashes
make one window; two empty fingerprints have likeness 1, one empty has 0; repeated
rows of one (doc_id, text) count as one document when the next document is sought;
a null ``doc_id`` comes first; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fragmap.llm import common

UNIT_CHARS = 12
GRAM = 3
WINDOW = 6
ID_RANGES = 256
_LOWEST = -(2**63)
_LOW = 2**32 - 1


def selected(text: Column, gram: int = GRAM, window: int = WINDOW) -> Column:
    """array<bigint>, each hash << 32 | (2**32 - 1 - position), in order of position."""
    units = F.regexp_extract_all(text, F.lit(r"((?<!\S)\S{1,%d}(?!\S)|\S)" % UNIT_CHARS), 1)

    def grams(us: Column) -> Column:
        last = F.greatest(F.size(us) - gram, F.lit(0))

        def hashed(i: Column) -> Column:
            h = F.xxhash64(*[F.get(us, i + j) for j in range(gram)])
            return F.shiftleft(h.bitwiseAND(F.lit(2**31 - 1)), 32).bitwiseOR(F.lit(_LOW) - i.cast("bigint"))

        return F.transform(F.sequence(F.lit(0), last), hashed)

    def minima(hs: Column) -> Column:
        starts = F.sequence(F.lit(1), F.greatest(F.size(hs) - window + 1, F.lit(1)))
        return F.array_distinct(F.transform(starts, lambda i: F.array_min(F.slice(hs, i, window))))

    none = F.array().cast("array<bigint>")
    return common.let(units, lambda us: F.when(F.size(us) == 0, none).otherwise(common.let(grams(us), minima)))


def hashes(sel: Column) -> Column:
    """Distinct hashes of a fingerprint, without positions."""
    return F.array_distinct(F.transform(sel, lambda v: F.shiftright(v, 32).cast("int")))


def fingerprint_text(sel: Column) -> Column:
    """hash@position, space-joined."""
    return F.array_join(
        F.transform(sel, lambda v: F.concat(F.hex(F.shiftright(v, 32)), F.lit("@"), (F.lit(_LOW) - v.bitwiseAND(F.lit(_LOW))).cast("string"))), " "
    )


def likeness(a: Column, b: Column) -> Column:
    """Jaccard of two arrays of distinct hashes."""
    both = F.size(F.array_intersect(a, b)).cast("double")
    either = F.size(a) + F.size(b) - both
    return F.when(either == 0, F.lit(1.0)).otherwise(both / either)


def successors(ids: DataFrame) -> DataFrame:
    """(doc, text_id, n, next_doc, next_text) of distinct documents in (doc, text_id) order, the last followed by the first.

    Ids are cut into ranges at their quantiles; each range is ordered by itself and
    only its first row crosses to the range before.
    """
    ids = common.checkpoint(ids.distinct())
    cuts = ids.agg(F.percentile_approx("doc", [i / ID_RANGES for i in range(1, ID_RANGES)], 10000).alias("cuts")).first()["cuts"]
    if not cuts:
        return ids.select("*", F.col("doc").alias("next_doc"), F.col("text_id").alias("next_text"))
    cuts = sorted(set(cuts))
    # array_position of the first cut above is a scan of at most ID_RANGES longs
    part = F.size(F.filter(F.array(*[F.lit(c).cast("bigint") for c in cuts]), lambda c: c < F.col("doc")))
    ranged = ids.withColumn("part", part)
    order = Window.partitionBy("part").orderBy("doc", "text_id")
    ranged = ranged.withColumns({"next_doc": F.lead("doc").over(order), "next_text": F.lead("text_id").over(order)})
    firsts = ids.withColumn("part", part).groupBy("part").agg(F.min(F.struct("doc", "text_id")).alias("head"))
    line = Window.orderBy("part")
    whole = line.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    after = firsts.select("part", F.coalesce(F.lead("head").over(line), F.first("head").over(whole)).alias("after"))
    return ranged.join(F.broadcast(after), "part").select(
        "doc", "text_id", "n",
        F.coalesce("next_doc", "after.doc").alias("next_doc"),
        F.when(F.col("next_doc").isNull(), F.col("after.text_id")).otherwise(F.col("next_text")).alias("next_text"),
    )


def edited_fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Fingerprints of every text, of its edited text and their likeness, one row per row of ``docs``.

    Texts cross the network once, hashed by document; the parts that a predecessor
    needs (a prefix and a set of hashes) once more.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    base = docs.select(
        F.coalesce(F.col(id_col).cast("bigint"), F.lit(_LOWEST)).alias("doc"), F.xxhash64(text).alias("text_id"), text.alias("text")
    )
    order = common.checkpoint(successors(base.select("doc", "text_id", F.length("text").cast("bigint").alias("n"))))
    wanted = order.select(
        F.col("next_doc").alias("doc"), F.col("next_text").alias("text_id"),
        F.col("doc").alias("for_doc"), F.col("text_id").alias("for_text"), F.col("n").alias("for_n"),
    )
    # both joins read base by the same three columns, so its exchange is made once
    given = (
        base.join(wanted.hint("shuffle_hash"), ["doc", "text_id"])
        .select(
            F.col("for_doc").alias("doc"), F.col("for_text").alias("text_id"),
            F.expr("left(text, cast(for_n div 4 as int))").alias("prefix"), hashes(selected(F.col("text"))).alias("next_hashes"),
        )
        .groupBy("doc", "text_id").agg(F.first("prefix").alias("prefix"), F.first("next_hashes").alias("next_hashes"))
    )
    joined = base.join(given.hint("shuffle_hash"), ["doc", "text_id"])
    n = F.length("text").cast("bigint")
    edited = F.concat(F.left("text", (n - F.floor(n / 4)).cast("int")), F.col("prefix"))
    doc_id = F.nullif(F.col("doc"), F.lit(_LOWEST)).alias("doc_id")
    rows = joined.select(doc_id, n.alias("n_chars"), "next_hashes", edited.alias("edited"), selected(F.col("text")).alias("sel"))
    rows = rows.withColumn("edited_sel", selected(F.col("edited")))
    return rows.select(
        "doc_id", "n_chars", F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"),
        fingerprint_text(F.col("sel")).alias("fingerprint"), fingerprint_text(F.col("edited_sel")).alias("edited_fingerprint"),
        likeness(hashes(F.col("sel")), hashes(F.col("edited_sel"))).alias("near_edited"),
        likeness(hashes(F.col("sel")), F.col("next_hashes")).alias("near_next"),
    )


def document_fingerprints(docs: DataFrame, text_col: str = "text", gram: int = GRAM, window: int = WINDOW) -> DataFrame:
    """All columns of ``docs`` (one named so as ``input_fingerprint``) and ``fingerprint``: array<struct<hash int, pos bigint>>."""
    pairs = F.transform(
        selected(F.coalesce(F.col(text_col), F.lit("")), gram, window),
        lambda v: F.struct(F.shiftright(v, 32).cast("int").alias("hash"), (F.lit(_LOW) - v.bitwiseAND(F.lit(_LOW))).alias("pos")),
    )
    return common.set_aside(docs, ["fingerprint"]).withColumn("fingerprint", pairs)


def op9_document_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edited_fingerprints(common.table(spark, sf_dir, "documents").select("doc_id", "text"))
