"""What the classifier is compared with."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..store import keep, offered
from ..functions.text import extension, tokens_of
from .features import Space, to_sparse, vectorize_sql
from .score import Linear


def by_extension(df: DataFrame, known: DataFrame) -> DataFrame:
    """The suffix, where it is a known class; null otherwise. df: filename, label."""
    classes = F.broadcast(known.select(F.col("label").alias("pred")).distinct())
    return df.withColumn("__e", extension(F.col("filename"))).join(classes, F.col("__e") == F.col("pred"), "left").drop("__e")


def by_origin(train: DataFrame, df: DataFrame) -> DataFrame:
    """The most frequent class of the file's origin; equal counts by name."""
    n = train.groupBy("origin", "label").agg(F.count("*").alias("n"))
    best = n.groupBy("origin").agg(F.min(F.struct((-F.col("n")).alias("k"), "label")).alias("b")).select("origin", F.col("b.label").alias("pred"))
    return df.join(offered(keep(best)), "origin", "left")  # origins may grow with the corpus


#: Cues of well-known formats: (pattern of the content, class).
CUES = (
    (r"^\s*<(!DOCTYPE|html)", "html_en"), (r"^\s*\{", "json"), (r"^\[[0-9]+\]\n", "ini"), (r"^<part>", "xml"), (r"^[0-9]+\|", "tbl"),
    (r"^[0-9]+,[0-9]+,", "csv"), (r"^[0-9]+\t", "tsv"), (r"^-?[0-9]+ -?[0-9]+ ", "vec"),
)


def by_cues(df: DataFrame, rules: tuple[tuple[str, str], ...] = CUES, default: str = "txt_en") -> DataFrame:
    """Hand-written rules, the first that fits."""
    out = None
    for pattern, name in rules:
        test = F.col("content").rlike(pattern)
        out = F.when(test, name) if out is None else out.when(test, name)
    return df.withColumn("pred", out.otherwise(default))


def prior(train: DataFrame, df: DataFrame) -> DataFrame:
    """The most frequent class."""
    best = train.groupBy("label").agg(F.count("*").alias("n")).agg(F.min(F.struct((-F.col("n")).alias("k"), "label")).alias("b")).select(F.col("b.label").alias("pred"))
    return df.crossJoin(F.broadcast(best))  # one row


def centroids(train: DataFrame, space: Space) -> DataFrame:
    """(label, idx, w): mean vector of each class, scaled to length one."""
    v = vectorize_sql(train, space, trimmed=True)
    size = train.groupBy("label").agg(F.count("*").alias("files"))
    mean = v.groupBy("label", "idx").agg(F.sum("freq").alias("s")).join(F.broadcast(size), "label").select("label", "idx", (F.col("s") / F.col("files")).alias("m"))
    return mean.withColumn("w", F.col("m") / F.sqrt(F.sum(F.col("m") * F.col("m")).over(Window.partitionBy("label")))).drop("m")


def nearest_centroid(train: DataFrame, df: DataFrame, space: Space) -> DataFrame:
    """(file_id, label, pred): the class of the largest cosine, equal ones by name. Empty files have no row."""
    c = centroids(train, space).withColumnRenamed("label", "pred")
    dots = vectorize_sql(df, space).join(F.broadcast(c), "idx").groupBy("file_id", "label", "pred").agg(F.sum(F.col("freq") * F.col("w")).alias("dot"))
    best = dots.groupBy("file_id", "label").agg(F.min(F.struct((-F.round("dot", 12)).alias("k"), "pred")).alias("b"))
    return best.select("file_id", "label", F.col("b.pred").alias("pred"))


def _indexed(vectors: DataFrame, classes: list[str]) -> DataFrame:
    return vectors.withColumn("y", F.array_position(F.array(*map(F.lit, classes)), F.col("label")).cast("double") - 1)


def logreg(vectors: DataFrame, size: int, steps: int = 60, ridge: float = 1e-4) -> Linear:
    """Multinomial logistic regression on CSR vectors."""
    from pyspark.ml.classification import LogisticRegression

    classes = sorted(r.label for r in vectors.select("label").distinct().collect())
    model = LogisticRegression(featuresCol="features", labelCol="y", maxIter=steps, regParam=ridge, family="multinomial").fit(_indexed(to_sparse(vectors, size), classes))
    return Linear(classes, np.asarray(model.coefficientMatrix.toArray()).T.copy(), np.asarray(model.interceptVector.toArray()))


def perceptron(vectors: DataFrame, size: int, hidden: tuple[int, ...] = (32,), steps: int = 60, seed: int = 42):
    """The library's own perceptron, without dropout or adaptive steps: (model, classes)."""
    from pyspark.ml.classification import MultilayerPerceptronClassifier

    classes = sorted(r.label for r in vectors.select("label").distinct().collect())
    net = MultilayerPerceptronClassifier(featuresCol="features", labelCol="y", layers=[size, *hidden, len(classes)], maxIter=steps, seed=seed)
    return net.fit(_indexed(to_sparse(vectors, size), classes)), classes


def hashed_features(tokens: Column, width: int = 4096) -> Column:
    """Hashed token and token-position features: a cheap stand-in for models of order."""
    placed = F.transform(tokens, lambda t, i: F.concat_ws("@", t, F.least((F.log2(i + 1)).cast("int"), F.lit(8)).cast("string")))
    return F.transform(F.concat(tokens, placed), lambda t: F.pmod(F.xxhash64(t), F.lit(width)).cast("int"))


def hashed_linear(train: DataFrame, test: DataFrame, width: int = 2048, steps: int = 40) -> DataFrame:
    """(file_id, label, pred): logistic regression over hashed features."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.feature import HashingTF

    classes = sorted(r.label for r in train.select("label").distinct().collect())
    tf = HashingTF(inputCol="h", outputCol="features", numFeatures=width)

    def prepared(df: DataFrame) -> DataFrame:
        return tf.transform(_indexed(df.select("file_id", "label", F.transform(hashed_features(tokens_of(F.col("content")), width), lambda x: x.cast("string")).alias("h")), classes))

    model = LogisticRegression(featuresCol="features", labelCol="y", maxIter=steps, regParam=1e-4).fit(prepared(train))
    names = F.array(*map(F.lit, classes))
    return model.transform(prepared(test)).select("file_id", "label", F.get(names, F.col("prediction").cast("int")).alias("pred"))


