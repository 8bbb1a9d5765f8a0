"""The four modules as Spark ML stages: augmentation, featurisation, learning, inference."""

from __future__ import annotations

from pyspark import keyword_only
from pyspark.ml import Estimator, Model, Transformer
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import augment, claims, resolver


class Augmenter(Transformer):
    """Records with those of synthetic entities added; `truth()` has the labels of both."""

    def __init__(self, attrs: list[str], seeds: DataFrame, ratio: float = 0.1, seed: int = 0, to: str = "any"):
        super().__init__()
        self.attrs, self.seeds, self.ratio, self.seed, self.to = list(attrs), seeds, ratio, seed, to
        self._truth: DataFrame | None = None

    def _transform(self, dataset: DataFrame) -> DataFrame:
        numbered = resolver.number_records(dataset, resolver.Settings(tuple(self.attrs)), "augmenter-records")
        records, self._truth = augment.augment_records(numbered, self.seeds.select(*claims.CELL, "value"), self.attrs, self.ratio, self.seed, self.to)
        return records

    def truth(self) -> DataFrame:
        return self.seeds if self._truth is None else self._truth


class Featurizer(Transformer):
    """Candidates with their static features: (entity_id, attr, value, support, slot, n_slots, static, sources)."""

    def __init__(self, settings: resolver.Settings):
        super().__init__()
        self.settings = settings

    def _transform(self, dataset: DataFrame) -> DataFrame:
        wide = resolver.number_records(dataset, self.settings, "featurizer-records")
        return resolver._static(wide, self.settings, resolver.source_list(wide, self.settings))[0].drop("_m")


class Resolver(Estimator):
    """Fits the stages on known entities; keyword arguments are those of `resolver.Settings`."""

    @keyword_only
    def __init__(self, *, attrs: list[str], seeds: DataFrame, **settings):
        super().__init__()
        self.seeds, self.settings = seeds, resolver.Settings(tuple(attrs), **settings)

    def _fit(self, dataset: DataFrame) -> ResolverModel:
        fitted, scored = resolver.fit(dataset, self.seeds, self.settings)
        return ResolverModel(fitted, scored)


class ResolverModel(Model):
    """Replays the fitted stages on records: (entity_id, attr, value, slot, p).  `scored` has those of the records fitted on."""

    def __init__(self, fitted: resolver.Fitted, scored: DataFrame | None = None):
        super().__init__()
        self.fitted, self.scored = fitted, scored

    def _transform(self, dataset: DataFrame) -> DataFrame:
        return resolver.resolve_new(self.fitted, dataset)

    def save(self, path: str) -> None:
        from pyspark.sql import SparkSession

        self.fitted.save(SparkSession.getActiveSession(), path)

    @staticmethod
    def load(path: str) -> ResolverModel:
        from pyspark.sql import SparkSession

        return ResolverModel(resolver.Fitted.load(SparkSession.getActiveSession(), path))


class Answers(Transformer):
    """One value a cell from scored candidates; known values stay where seeds are given."""

    def __init__(self, seeds: DataFrame | None = None, pick: str = "argmax", seed: int = 0):
        super().__init__()
        self.seeds, self.pick, self.seed = seeds, pick, seed

    def _transform(self, dataset: DataFrame) -> DataFrame:
        return resolver.resolve(dataset, self.seeds, self.pick, self.seed).where(F.col("value").isNotNull())
