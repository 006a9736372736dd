"""Rewrites that hold because results are kept independently."""

from __future__ import annotations

from pyspark.sql import Column

from joinpoisson.plans.relations import RelationSpec


def push_selection(specs: list[RelationSpec], conditions: dict[str, Column]) -> list[RelationSpec]:
    """A selection on one relation's tuples before sampling has the law of the same selection on the sample: with it the
    index only counts the selected part. conditions: relation -> condition on its columns."""
    unknown = set(conditions) - {s.name for s in specs}
    if unknown:
        raise ValueError(f"no such relations: {sorted(unknown)}")
    return [RelationSpec(s.name, s.df.where(conditions[s.name]) if s.name in conditions else s.df, s.attrs) for s in specs]
