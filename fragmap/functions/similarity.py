"""Word and phrase similarity: vectors, a lexicon of synonyms, character n-grams.

A model scores (word, target word) in [0, 1]. A phrase scores, by default, the mean over
its words of the best target word. Identical stems score 1, unknown words 0.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BESTMEAN, CENTROID = "bestmean", "centroid"


def words_in(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), r"[^a-z0-9_#]+"), lambda w: w != "")


def ngrams(word: Column, n: int = 3) -> Column:
    """Distinct character n-grams; a shorter word is its own."""
    return F.when(F.length(word) < n, F.array(word)).otherwise(
        F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.length(word) - n + 1, F.lit(1))), lambda i: F.substring(word, i, n)))
    )


def ngram_similarity(a: Column, b: Column, n: int = 3, measure: str = "dice") -> Column:
    x, y = ngrams(a, n), ngrams(b, n)
    both = F.size(F.array_intersect(x, y)).cast("double")
    return 2 * both / (F.size(x) + F.size(y)) if measure == "dice" else both / F.size(F.array_union(x, y))


def cosine(a: Column, b: Column) -> Column:
    """Cosine of two arrays in double precision; 0 where one has no length."""
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    size = F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))
    return F.when(size > 0, dot(a, b) / size).otherwise(0.0)


class SimilarityModel:
    """``pair(w, t)`` frames must give (word, target, score) for distinct pairs of words with a score above 0."""

    def word_scores(self, pairs: DataFrame) -> DataFrame:
        raise NotImplementedError

    def score(self, pairs: DataFrame, words: str = "words", targets: str = "targets", phrase: str = BESTMEAN) -> DataFrame:
        """``pairs`` with arrays of stems and ``sigma``; each distinct (word, target) is looked up once."""
        keyed = pairs.select(words, targets).distinct()
        grid = keyed.select(words, targets, F.posexplode(words).alias("at", "word")).select(words, targets, "at", "word", F.explode(targets).alias("target"))
        found = self.word_scores(grid.select("word", "target").distinct())
        best = (
            grid.join(found, ["word", "target"], "left").groupBy(words, targets, "at")
            .agg(F.max(F.coalesce("score", F.lit(0.0))).alias("best"), F.avg(F.coalesce("score", F.lit(0.0))).alias("mean"))
        )
        value = "best" if phrase == BESTMEAN else "mean"
        sigma = best.groupBy(words, targets).agg(F.round(F.avg(value), 9).alias("sigma"))
        return pairs.join(sigma, [words, targets], "left").withColumn("sigma", F.coalesce("sigma", F.lit(0.0)))


class LexiconSimilarity(SimilarityModel):
    """``glossary`` (word, synonym, score) of stems, read both ways."""

    def __init__(self, glossary: DataFrame):
        self.glossary = glossary

    def word_scores(self, pairs: DataFrame) -> DataFrame:
        g = self.glossary.unionByName(self.glossary.select(F.col("synonym").alias("word"), F.col("word").alias("synonym"), "score"))
        g = g.groupBy("word", F.col("synonym").alias("target")).agg(F.max("score").alias("score"))
        joined = pairs.join(g, ["word", "target"], "left")
        return joined.select("word", "target", F.when(F.col("word") == F.col("target"), 1.0).otherwise(F.col("score")).alias("score")).where("score > 0")


class NgramSimilarity(SimilarityModel):
    def __init__(self, n: int = 3, measure: str = "dice"):
        self.n, self.measure = n, measure

    def word_scores(self, pairs: DataFrame) -> DataFrame:
        return pairs.withColumn("score", ngram_similarity(F.col("word"), F.col("target"), self.n, self.measure)).where("score > 0")


class VectorSimilarity(SimilarityModel):
    """``vectors`` (word, v array<float>); cosines are moved to [0, 1] unless ``rescale`` is off."""

    def __init__(self, vectors: DataFrame, rescale: bool = True):
        self.vectors, self.rescale = vectors, rescale

    def word_scores(self, pairs: DataFrame) -> DataFrame:
        a = self.vectors.select("word", F.col("v").alias("_a"))
        b = self.vectors.select(F.col("word").alias("target"), F.col("v").alias("_b"))
        c = cosine(F.col("_a"), F.col("_b"))
        value = (c + 1) / 2 if self.rescale else F.greatest(c, F.lit(0.0))
        joined = pairs.join(a, "word", "left").join(b, "target", "left")
        return joined.select(
            "word", "target", F.when(F.col("word") == F.col("target"), 1.0).when(F.col("_a").isNull() | F.col("_b").isNull(), 0.0).otherwise(value).alias("score")
        ).where("score > 0")


def train_vectors(sentences: DataFrame, size: int = 32, min_count: int = 2, seed: int = 7) -> DataFrame:
    """Word vectors from (words array<string>) rows: log, schema and document text."""
    from pyspark.ml.feature import Word2Vec
    from pyspark.ml.functions import vector_to_array

    model = Word2Vec(vectorSize=size, minCount=min_count, seed=seed, inputCol="words", outputCol="v").fit(sentences)
    return model.getVectors().select("word", vector_to_array("vector").cast("array<float>").alias("v"))
