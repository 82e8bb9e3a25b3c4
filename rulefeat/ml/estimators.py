"""The selector and the binner as stages of Spark's pipelines."""

from __future__ import annotations

import json

from pyspark import keyword_only
from pyspark.ml import Estimator, Model
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.ml.util import DefaultParamsReadable, DefaultParamsWritable
from pyspark.sql import DataFrame

from ..operators.binning import BinnerModel, EntropyBinner
from ..operators.features import apply
from ..operators.selectors import select_balanced, select_nonredundant


class _Settings(Params):
    labelCol = Param(Params._dummy(), "labelCol", "label column", TypeConverters.toString)
    categorical = Param(Params._dummy(), "categorical", "categorical columns", TypeConverters.toListString)
    continuous = Param(Params._dummy(), "continuous", "continuous columns", TypeConverters.toListString)
    k = Param(Params._dummy(), "k", "intervals for each continuous column", TypeConverters.toInt)
    parts = Param(Params._dummy(), "parts", "quantiles tried in each interval", TypeConverters.toInt)
    dFreq = Param(Params._dummy(), "dFreq", "frequent sets", TypeConverters.toInt)
    dConf = Param(Params._dummy(), "dConf", "rules", TypeConverters.toInt)
    redundancy = Param(Params._dummy(), "redundancy", "strict, printed or none", TypeConverters.toString)
    margin = Param(Params._dummy(), "margin", "factor on the main effects' score", TypeConverters.toFloat)
    fitted = Param(Params._dummy(), "fitted", "cuts and features as JSON", TypeConverters.toString)

    def __init__(self):
        super().__init__()
        self._setDefault(labelCol="y", categorical=[], continuous=[], k=4, parts=20, dFreq=30, dConf=15, redundancy="strict", margin=1.0, fitted="{}")


class MixedRuleFeatures(_Settings, Estimator, DefaultParamsReadable, DefaultParamsWritable):
    """Bins continuous columns, keeps categorical ones, and selects binary features of both by rules."""

    @keyword_only
    def __init__(self, *, labelCol="y", categorical=None, continuous=None, k=4, parts=20, dFreq=30, dConf=15, redundancy="strict", margin=1.0):
        super().__init__()
        self._set(**{n: v for n, v in self._input_kwargs.items() if v is not None})

    def _fit(self, df: DataFrame) -> MixedRuleFeaturesModel:
        get = self.getOrDefault
        binner = EntropyBinner(get("k"), get("parts"), get("continuous"), get("labelCol")).fit(df)
        binned = binner.transform(df) if get("continuous") else df
        columns = [*get("categorical"), *(f"{c}_bin" for c in get("continuous"))]
        if get("redundancy") == "none":
            found = select_balanced(binned, get("labelCol"), columns, get("dFreq"), get("dConf"))
        else:
            found = select_nonredundant(binned, get("labelCol"), columns, get("dFreq"), get("dConf"), redundancy=get("redundancy"), margin=get("margin"))
        rows = sorted((r.asDict() for r in found.features.collect()), key=lambda r: r["feature_id"])
        kept = json.dumps({"cuts": {str(f): c for f, c in binner.cuts.items()}, "features": rows})
        return self._copyValues(MixedRuleFeaturesModel())._set(fitted=kept)


class MixedRuleFeaturesModel(_Settings, Model, DefaultParamsReadable, DefaultParamsWritable):
    """Adds the binned columns and a 0/1 column for each feature; what was fitted is a parameter, so the model is saved like any stage."""

    @property
    def binner(self) -> BinnerModel:
        cuts = json.loads(self.getOrDefault("fitted"))["cuts"]
        return BinnerModel(self.getOrDefault("continuous"), {int(f): [tuple(c) for c in cs] for f, cs in cuts.items()})

    @property
    def rows(self) -> list[dict]:
        return json.loads(self.getOrDefault("fitted"))["features"]

    @property
    def columns(self) -> list[str]:
        return [*self.getOrDefault("categorical"), *(f"{c}_bin" for c in self.getOrDefault("continuous"))]

    def _transform(self, df: DataFrame) -> DataFrame:
        binned = self.binner.transform(df) if self.getOrDefault("continuous") else df
        return apply(binned, self.rows, self.columns)
