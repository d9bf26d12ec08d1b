"""The concept closure as a DataFrame, for ontologies that outgrow a driver."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathlore.operators.staging import release, stage
from pathlore.plans.ontology import Ontology
from pathlore.plans.terms import Role


def direct_inclusions(spark: SparkSession, onto: Ontology) -> DataFrame:
    """(below, above) of the axioms, existences following the role axioms."""
    rows = {(str(a.left), str(a.right)) for a in onto.concepts if not a.negative}
    for a in onto.roles:
        if not a.negative and isinstance(a.left, Role):
            rows |= {(f"exists {a.left}", f"exists {a.right}"), (f"exists {a.left.inv()}", f"exists {a.right.inv()}")}
    return spark.createDataFrame(sorted(rows), "below string, above string")


def saturate_concepts_df(inclusions: DataFrame, max_rounds: int = 64) -> DataFrame:
    """Transitive closure of (below, above) by doubling: rounds grow with the logarithm of the longest chain."""
    seen = stage(inclusions.where("below <> above").distinct(), "closure")
    count = seen.count()
    for _ in range(max_rounds):
        longer = seen.alias("a").join(seen.alias("b"), F.col("a.above") == F.col("b.below")).select(F.col("a.below").alias("below"), F.col("b.above").alias("above"))
        before = seen
        seen = stage(seen.unionByName(longer).where("below <> above").distinct(), "closure")
        release(before)
        now = seen.count()
        if now == count:
            return seen
        count = now
    raise RuntimeError("the closure did not settle")
