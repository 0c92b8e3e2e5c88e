"""The classic forest: samples as copied rows, random features at each node, every tree one vote."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..operators.binning import BinRule
from ..operators.growth import functional_weights
from ..operators.model import Forest, fit_binned
from ..operators.spec import ForestSpec


def fit(rows: DataFrame, rules: list[BinRule], classes: list, spec: ForestSpec, all_features: bool = False, copies: bool = False, alike: DataFrame | None = None) -> Forest:
    """all_features scores every feature at each node in place of a random draw. copies stores a row for each time it
    is drawn and trains on slices of these; without, equal weights stand for them, which gives the same trees. alike: as for fit_binned."""
    own = spec.but(reduction=False, vote="direct", sampling="poisson", feature_draw="tree" if all_features else "node")
    if not copies:
        return fit_binned(rows, rules, classes, own, alike=alike)
    drawn = functional_weights(rows, list(range(spec.n_trees)), spec.seed)
    return fit_binned(rows, rules, classes, own.but(layout="vertical", sampling="copied"), drawn)
