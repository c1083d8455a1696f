"""What the cleaned database is for: one row an entity with its attributes and events."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def visits_per_entity(entities: DataFrame, sk: str, name: str, events: DataFrame, fk: str, when: str) -> DataFrame:
    """entity, name, n_events, n_dates; events are counted before the join, so an entity's row is joined once."""
    counted = events.groupBy(F.col(fk).alias("entity")).agg(F.count(F.lit(1)).alias("n_events"), F.countDistinct(when).alias("n_dates"))
    return entities.select(F.col(sk).alias("entity"), F.col(name).alias("name")).join(counted, "entity")
