"""The contrast of an engine that writes and reads all state between steps."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..operators.binning import BinRule
from ..operators.model import Forest, fit_binned
from ..operators.spec import ForestSpec


def fit(rows: DataFrame, rules: list[BinRule], classes: list, spec: ForestSpec) -> Forest:
    return fit_binned(rows, rules, classes, spec.but(state="disk"))
