"""The classifier as stages of the ML library's pipelines."""

from __future__ import annotations

import json

import numpy as np
from pyspark import keyword_only
from pyspark.ml import Estimator, Model
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.ml.param.shared import HasLabelCol, HasPredictionCol, HasSeed
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import balance, nb, score, splits
from .operators.features import Config, Space, learn_space, vectorize
from .operators.mlp import Net, Spec, fit


class _Shared(HasLabelCol, HasPredictionCol, HasSeed):
    contentCol = Param(Params._dummy(), "contentCol", "content column", TypeConverters.toString)
    network = Param(Params._dummy(), "network", "hidden widths; empty for naive Bayes", TypeConverters.toListInt)
    lr = Param(Params._dummy(), "lr", "learning rate", TypeConverters.toFloat)
    epochs = Param(Params._dummy(), "epochs", "training epochs", TypeConverters.toInt)


class FileKindEstimator(Estimator, _Shared):
    """Learns vocabulary, vectors and classifier from labelled contents."""

    @keyword_only
    def __init__(self, *, contentCol="content", labelCol="label", predictionCol="pred", network=(), lr=1e-3, epochs=8, seed=42):
        super().__init__()
        self._setDefault(contentCol="content", labelCol="label", predictionCol="pred", network=[], lr=1e-3, epochs=8, seed=42)
        self._set(**{**self._input_kwargs, "network": list(network)} if "network" in self._input_kwargs else self._input_kwargs)

    def _fit(self, df: DataFrame) -> FileKindModel:
        c = F.col(self.getOrDefault("contentCol"))
        rows = df.select(F.sha1(c).alias("sha"), c.alias("content"), F.col(self.getLabelCol()).alias("label")).withColumn("file_id", F.col("sha"))
        parts = splits.assign(rows, {"vocab": 20, "train": 60, "val": 20}, self.getSeed())
        train = balance.undersample(parts.where("split <> 'val'"), self.getSeed(), within=("split",)).cache()
        space = learn_space(train.where("split = 'vocab'"), Config())
        files = train.where("split = 'train'")
        hidden = tuple(self.getOrDefault("network"))
        if hidden:
            spec = Spec(hidden=hidden, lr=self.getOrDefault("lr"), epochs=self.getOrDefault("epochs"), seed=self.getSeed())
            net = fit(vectorize(files, space, True), vectorize(parts.where("split = 'val'"), space), space.size, spec)
        else:
            net = nb.fit(files, space)
        train.unpersist()
        return FileKindModel(net, space)._resetUid(self.uid)._copy(self)


class FileKindModel(Model, _Shared):
    def __init__(self, net=None, space: Space | None = None):
        super().__init__()
        self._setDefault(contentCol="content", labelCol="label", predictionCol="pred", network=[], lr=1e-3, epochs=8, seed=42)
        self.net, self.space = net, space

    def _copy(self, other: Params) -> FileKindModel:
        for p, v in other.extractParamMap().items():
            if self.hasParam(p.name):
                self._set(**{p.name: v})
        return self

    def _transform(self, df: DataFrame) -> DataFrame:
        out = score.predict(df.withColumn("content", F.col(self.getOrDefault("contentCol"))), self.net, self.space, keep=tuple(df.columns))
        return out.withColumnRenamed("pred", self.getPredictionCol())

    def save(self, path: str) -> None:
        spark = SparkSession.active()
        cfg = vars(self.space.cfg) | {"tau": {str(k): list(v) for k, v in self.space.cfg.tau.items()}}
        layers = [(w.tolist(), b.tolist()) for w, b in zip(self.net.weights, self.net.biases)] if isinstance(self.net, Net) else [(self.net.weights.tolist(), self.net.bias.tolist())]
        spec = {"classes": self.net.classes, "network": isinstance(self.net, Net), "terms": {str(k): v for k, v in self.space.terms.items()}, "cfg": cfg, "params": {p.name: v for p, v in self.extractParamMap().items()}}
        rows = [(-1, json.dumps(spec))] + [(k, json.dumps(x)) for k, x in enumerate(layers)]
        spark.createDataFrame(rows, "layer int, json string").write.parquet(path)

    @staticmethod
    def load(path: str) -> FileKindModel:
        rows = {r["layer"]: json.loads(r["json"]) for r in SparkSession.active().read.parquet(path).collect()}
        spec = rows.pop(-1)
        cfg = spec["cfg"] | {"tau": {int(k): tuple(v) for k, v in spec["cfg"]["tau"].items()}, "orders": tuple(spec["cfg"]["orders"])}
        layers = [rows[k] for k in sorted(rows)]
        if spec["network"]:
            net = Net(spec["classes"], [np.array(w, np.float32) for w, _ in layers], [np.array(b, np.float32) for _, b in layers])
        else:
            net = score.Linear(spec["classes"], np.array(layers[0][0]), np.array(layers[0][1]))
        out = FileKindModel(net, Space({int(k): v for k, v in spec["terms"].items()}, Config(**cfg)))
        out._set(**{k: v for k, v in spec["params"].items() if out.hasParam(k)})
        return out
