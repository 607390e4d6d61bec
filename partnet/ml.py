"""The pipeline form: an estimator that fits a bottleneck on rows and a model that labels rows."""

from __future__ import annotations

import json

from pyspark import keyword_only
from pyspark.ml import Estimator, Model
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.ml.util import DefaultParamsReadable, DefaultParamsWritable
from pyspark.sql import DataFrame

from partnet.operators.apply import assign
from partnet.operators.joint import build_joint
from partnet.operators.solve import StopRule, bind, solve
from partnet.plans.graph import BottleneckSpec, TradeOff
from partnet.sources.tables import cut_lineage, load_partitions, save_partitions


class _Settings(Params):
    spec = Param(Params._dummy(), "spec", "specification as JSON", TypeConverters.toString)
    sizes = Param(Params._dummy(), "sizes", "clusters per cluster variable as JSON", TypeConverters.toString)
    trade = Param(Params._dummy(), "trade", "weight of the specification's objective", TypeConverters.toFloat)
    maxIter = Param(Params._dummy(), "maxIter", "most sweeps", TypeConverters.toInt)
    tol = Param(Params._dummy(), "tol", "stop below this largest move", TypeConverters.toFloat)
    seed = Param(Params._dummy(), "seed", "seed of a random start, -1 for the rank start", TypeConverters.toInt)


class BottleneckEstimator(Estimator, _Settings, DefaultParamsReadable, DefaultParamsWritable):
    @keyword_only
    def __init__(self, spec: str | None = None, sizes: str | None = None, trade: float = 5.0, maxIter: int = 30, tol: float = 1e-5, seed: int = -1):  # noqa: N803
        super().__init__()
        self._setDefault(trade=5.0, maxIter=30, tol=1e-5, seed=-1)
        self._set(**{k: v for k, v in self._input_kwargs.items() if v is not None})

    @classmethod
    def of(cls, spec: BottleneckSpec, sizes: dict[str, int], **settings) -> BottleneckEstimator:
        return cls(spec=spec.to_json(), sizes=json.dumps(sizes), **settings)

    def _fit(self, dataset: DataFrame) -> BottleneckModel:
        spec, seed = BottleneckSpec.from_json(self.getOrDefault("spec")), self.getOrDefault("seed")
        joint = cut_lineage(build_joint(dataset, list(spec.observed)))
        model = bind(joint, spec, json.loads(self.getOrDefault("sizes")), "rank" if seed < 0 else "random", max(seed, 0))
        trade = TradeOff(spec.objective, self.getOrDefault("trade"))
        parts = solve(model, trade, stop=StopRule(self.getOrDefault("tol"), self.getOrDefault("maxIter"))).model.parts
        return BottleneckModel(spec, parts)


class BottleneckModel(Model):
    """Adds <cluster>_label and <cluster>_confidence; rows with unseen values get nulls."""

    def __init__(self, spec: BottleneckSpec, parts: dict[str, DataFrame]):
        super().__init__()
        self.spec, self.parts = spec, parts

    def _transform(self, dataset: DataFrame) -> DataFrame:
        for t in self.spec.clusters:
            sources = list(self.spec.sources(t))
            labels = assign(self.parts[t], sources).withColumnsRenamed({"t": f"{t}_label", "confidence": f"{t}_confidence"})
            dataset = dataset.join(labels, sources, "left")
        return dataset

    def save(self, path: str) -> None:
        save_partitions(self.parts, self.spec.to_json(), path)

    @classmethod
    def load(cls, spark, path: str) -> BottleneckModel:
        parts, spec = load_partitions(spark, path)
        return cls(BottleneckSpec.from_json(json.dumps(spec)), parts)
