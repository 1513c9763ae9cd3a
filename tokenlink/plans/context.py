"""What queries share: person views and intermediate results over one directory, built when first used."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import evaluate, lifecycle, linkage, present, weights
from ..operators.rules import RuleSet
from ..operators.standardize import standardize
from ..operators.tokens import tokens_long
from ..sources import personas
from ..sources.tables import Tables
from ..sources.written import materialize

#: Loose rules that make candidate pairs for the weighted methods.
LOOSE = RuleSet.of("S4 B", "L F3 B", "L~ F~ B", "L M F Y")


class Context:
    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.t = spark, Tables(spark, path)

    @cached_property
    def register_raw(self) -> DataFrame:
        return personas.register_raw(self.t)

    @cached_property
    def clinic_raw(self) -> DataFrame:
        return personas.clinic_raw(self.t)

    @cached_property
    def register(self) -> DataFrame:
        return standardize(self.register_raw, "reg_id")

    @cached_property
    def clinic(self) -> DataFrame:
        return standardize(self.clinic_raw, "clinic_id")

    @cached_property
    def clinic_db(self) -> DataFrame:
        return materialize(linkage.file_db(self.clinic))

    @cached_property
    def register_db(self) -> DataFrame:
        """The register's counts of the clinic's keys; the validation subset's keys are among them."""
        return materialize(linkage.token_db(linkage.reduce_to(tokens_long(self.register, keep=("death_date",)), self.clinic_db)))

    @cached_property
    def pairs(self) -> DataFrame:
        return linkage.one_to_one(linkage.file_db(linkage.validation_subset(self.clinic)), self.register_db)

    @cached_property
    def scores(self) -> DataFrame:
        return materialize(evaluate.scorecard(self.pairs))

    @cached_property
    def priority(self) -> DataFrame:
        return present.rule_priority(self.scores)

    @cached_property
    def links(self) -> DataFrame:
        return linkage.one_to_one(self.clinic_db, self.register_db).drop("token")

    @cached_property
    def best(self) -> DataFrame:
        return present.best_link(self.links, self.priority)

    @cached_property
    def presented(self) -> DataFrame:
        return present.present(self.clinic, self.best)

    @cached_property
    def corrected(self) -> DataFrame:
        return lifecycle.latest(personas.deliveries(self.t), "person", ("version", "dod"), ("version", "dod"))

    @cached_property
    def register2(self) -> DataFrame:
        """The register with the dates of the latest deliveries."""
        new = self.corrected.select(F.col("person").alias("rec_id"), F.col("dod").alias("__new"))
        return self.register.join(new, "rec_id", "left").withColumn("death_date", F.coalesce("__new", "death_date")).drop("__new")

    @cached_property
    def best2(self) -> DataFrame:
        return present.best_link(linkage.links(self.clinic, self.register2), self.priority)

    @cached_property
    def encounters(self) -> DataFrame:
        return personas.encounters(self.t)

    @cached_property
    def candidates(self) -> DataFrame:
        return materialize(linkage.candidates(self.clinic, self.register, LOOSE))

    @cached_property
    def weights(self) -> DataFrame:
        return weights.value_weights(self.register)

    @cached_property
    def pair_scores(self) -> DataFrame:
        return weights.score_pairs(self.candidates, self.clinic, self.register, self.weights)

    @cached_property
    def classes(self) -> DataFrame:
        more = ["birth_state", "race", "marital", "father_surname"]
        with_more = lambda std, raw, key: std.join(raw.select(F.col(key).alias("rec_id"), *more), "rec_id")
        return weights.classified(self.candidates, with_more(self.clinic, self.clinic_raw, "clinic_id"), with_more(self.register, self.register_raw, "reg_id"))

    @cached_property
    def chosen(self) -> DataFrame:
        """The weighted method's choice among each patient's candidates."""
        return weights.select_best(self.classes.join(self.pair_scores, ["clinic_id", "reg_id"]))
