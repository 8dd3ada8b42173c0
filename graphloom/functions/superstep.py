"""One superstep: write a table, and read scalar metrics off the same job."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, Observation

from graphloom.plans.scratch import Scratch


def observed(df: DataFrame, scratch: Scratch, name: str, **metrics: Column) -> tuple[DataFrame, dict]:
    """Save df to the scratch; the metrics are aggregated on the way, without a second pass."""
    watch = Observation(f"{name}-{uuid.uuid4().hex[:8]}")
    saved = scratch.save(df.observe(watch, *[c.alias(k) for k, c in metrics.items()]), name)
    return saved, watch.get
