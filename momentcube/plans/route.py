"""Choosing a materialised cube for a query before Catalyst sees it."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from ..summary import SummarySpec


@dataclass(frozen=True)
class Cube:
    name: str
    dims: frozenset[str]
    spec: SummarySpec
    cells: int
    table: DataFrame


def choose(cubes: list[Cube], dims: set[str], filters: set[str], spec: SummarySpec) -> Cube | None:
    """The smallest cube that has all dimensions asked for or filtered and the same kind of summary of enough orders; None: use raw rows."""
    fit = lambda c: dims | filters <= c.dims and c.spec.order >= spec.order and (c.spec.log_policy, c.spec.shift) == (spec.log_policy, spec.shift) and c.spec.power >= spec.power and c.spec.log >= spec.log
    return min(filter(fit, cubes), key=lambda c: (c.cells, c.name), default=None)
