"""Encoders: text to a unit vector."""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

_TOKEN = re.compile("[a-z0-9]+")


class Encoder:
    """``transform(df, in_col, out_col)`` adds an array<float> column of ``dim`` values."""

    dim: int

    def transform(self, df: DataFrame, in_col: str, out_col: str) -> DataFrame:
        raise NotImplementedError


def word_buckets(df: DataFrame, key: list[str], text: str, dim: int = 64) -> DataFrame:
    """key, bucket, value: signed hashed words with square-root counts, unit length. Native, and the same in SQL.

    A word's bucket is the first 8 digits of its MD5 modulo ``dim``, its sign the 9th digit.
    """
    words = df.select(*key, F.explode(F.regexp_extract_all(F.lower(text), F.lit("[a-z0-9]+"), F.lit(0))).alias("word")).groupBy(*key, "word").count()
    digest = F.md5("word")
    cells = words.select(*key, (F.conv(F.substring(digest, 1, 8), 16, 10).cast("long") % dim).cast("int").alias("bucket"), (F.when(F.substring(digest, 9, 1) < "8", 1.0).otherwise(-1.0) * F.sqrt("count")).alias("part"))
    cells = cells.groupBy(*key, "bucket").agg(F.round(F.sum("part"), 9).alias("raw"))
    norms = cells.groupBy(*key).agg(F.sqrt(F.sum(F.col("raw") * F.col("raw"))).alias("norm"))
    return cells.join(norms, key).select(*key, "bucket", F.when(F.col("norm") > 0, F.col("raw") / F.col("norm")).otherwise(0.0).alias("value"))


def word_vectors(df: DataFrame, key: list[str], text: str, dim: int = 64) -> DataFrame:
    """key, x (array<double>): the same vectors whole, in one Arrow pass without a shuffle. A text without words is all zeros."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = [_unit(_signed(_counts(_TOKEN.findall((t or "").lower())), dim)) for t in batch.column(len(key)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(key)], pa.array(x, pa.list_(pa.float64()))], [*key, "x"])

    kinds = ", ".join(f"{c} {df.schema[c].dataType.simpleString()}" for c in key)
    return df.select(*key, text).mapInArrow(run, f"{kinds}, x array<double>")


class WordHash(Encoder):
    """The same vectors as a column of floats."""

    def __init__(self, dim: int = 64):
        self.dim = dim

    def transform(self, df: DataFrame, in_col: str, out_col: str) -> DataFrame:
        dim = self.dim

        def cells(text: str) -> np.ndarray:
            return hashed(_counts(_TOKEN.findall(text.lower())), dim)

        @F.pandas_udf(T.ArrayType(T.FloatType()))
        def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
            for texts in batches:
                yield pd.Series([cells(t or "") for t in texts])

        return df.withColumn(out_col, run(in_col))


def _counts(features: list[str], weight: float = 1.0) -> dict[str, float]:
    out: dict[str, float] = {}
    for f in features:
        out[f] = out.get(f, 0.0) + 1
    return {f: weight * n**0.5 for f, n in out.items()}


def _signed(weights: dict[str, float], dim: int) -> np.ndarray:
    out = np.zeros(dim)
    for feature, w in weights.items():
        digest = hashlib.md5(feature.encode()).hexdigest()
        out[int(digest[:8], 16) % dim] += w if digest[8] < "8" else -w
    return np.round(out, 9)


def _unit(x: np.ndarray) -> np.ndarray:
    norm = np.sqrt((x * x).sum())
    return x / norm if norm else x


def hashed(weights: dict[str, float], dim: int) -> np.ndarray:
    return _unit(_signed(weights, dim)).astype(np.float32)


class HashedNgram(Encoder):
    """Words, word pairs and character n-grams, hashed; Arrow batches, no state."""

    def __init__(self, dim: int = 768, word: tuple[int, ...] = (1, 2), char: tuple[int, ...] = (3, 4), char_weight: float = 0.5):
        self.dim, self.word, self.char, self.char_weight = dim, word, char, char_weight

    def vector(self, text: str) -> np.ndarray:
        words = _TOKEN.findall(text.lower())
        weights = _counts([" ".join(words[i : i + n]) for n in self.word for i in range(len(words) - n + 1)])
        padded = [f"^{w}$" for w in words]
        grams = _counts([w[i : i + n] for w in padded for n in self.char for i in range(len(w) - n + 1)], self.char_weight)
        return hashed(weights | {f"#{g}": v for g, v in grams.items()}, self.dim)

    def transform(self, df: DataFrame, in_col: str, out_col: str) -> DataFrame:
        vector = self.vector

        @F.pandas_udf(T.ArrayType(T.FloatType()))
        def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
            for texts in batches:
                yield pd.Series([vector(t or "") for t in texts])

        return df.withColumn(out_col, run(in_col))


class HashedTfIdf(Encoder):
    """Hashed words weighted by inverse document frequency; one pass over the column for the frequencies."""

    def __init__(self, dim: int = 768):
        self.dim = dim

    def transform(self, df: DataFrame, in_col: str, out_col: str) -> DataFrame:
        from pyspark.ml.feature import IDF, HashingTF, Normalizer, RegexTokenizer
        from pyspark.ml.functions import vector_to_array

        rows = RegexTokenizer(inputCol=in_col, outputCol="_words", pattern="[a-z0-9]+", gaps=False, minTokenLength=1).transform(df)
        rows = HashingTF(inputCol="_words", outputCol="_tf", numFeatures=self.dim).transform(rows)
        rows = IDF(inputCol="_tf", outputCol="_idf").fit(rows).transform(rows)
        rows = Normalizer(inputCol="_idf", outputCol="_unit").transform(rows)
        return rows.withColumn(out_col, vector_to_array("_unit", "float32")).drop("_words", "_tf", "_idf", "_unit")


class Word2VecPooled(Encoder):
    """Trained word vectors, mean-pooled."""

    def __init__(self, dim: int = 64, seed: int = 1, min_count: int = 1):
        self.dim, self.seed, self.min_count = dim, seed, min_count

    def transform(self, df: DataFrame, in_col: str, out_col: str) -> DataFrame:
        from pyspark.ml.feature import RegexTokenizer, Word2Vec
        from pyspark.ml.functions import vector_to_array

        rows = RegexTokenizer(inputCol=in_col, outputCol="_words", pattern="[a-z0-9]+", gaps=False).transform(df)
        model = Word2Vec(inputCol="_words", outputCol="_vec", vectorSize=self.dim, minCount=self.min_count, seed=self.seed).fit(rows)
        return model.transform(rows).withColumn(out_col, vector_to_array("_vec", "float32")).drop("_words", "_vec")


class Precomputed(Encoder):
    """Vectors from a table (key, vector)."""

    def __init__(self, vectors: DataFrame, key: str, vector: str):
        self.vectors, self.key, self.vector = vectors, key, vector

    def transform(self, df: DataFrame, in_col: str, out_col: str) -> DataFrame:
        return df.join(self.vectors.select(F.col(self.key).alias(in_col), F.col(self.vector).alias(out_col)), in_col)


class ExternalModel(Encoder):
    """A sentence model that ``loader`` makes once per worker; ``loader()`` returns a function from a list of texts to a 2-d array."""

    def __init__(self, loader, dim: int):
        self.loader, self.dim = loader, dim

    def transform(self, df: DataFrame, in_col: str, out_col: str) -> DataFrame:
        loader = self.loader

        @F.pandas_udf(T.ArrayType(T.FloatType()))
        def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
            model = loader()
            for texts in batches:
                yield pd.Series(list(np.asarray(model(texts.fillna("").tolist()), np.float32)))

        return df.withColumn(out_col, run(in_col))
