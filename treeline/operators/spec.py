"""What a forest is to be: one specification for all methods, variants and ablations."""

from __future__ import annotations

import math
import warnings
from dataclasses import dataclass, replace


#: What a specification may say.
CHOICES = {
    "task": ("classification", "regression"),
    "criterion": ("gain_ratio", "gain", "gini"),
    "tree": ("c45", "cart"),
    "reduction_scope": ("tree", "shared"),
    "feature_draw": ("tree", "node"),
    "sampling": ("poisson", "multinomial", "copied"),
    "sampling_scope": ("global", "partition"),
    "layout": ("horizontal", "vertical", "blocks", "auto"),
    "parallel": ("both", "trees", "features", "none"),
    "vote": ("weighted", "direct"),
    "state": ("memory", "disk"),
}


@dataclass(frozen=True)
class ForestSpec:
    task: str = "classification"  # or "regression"
    n_trees: int = 20
    n_principal: int | None = None
    n_selected: int | None = None
    max_depth: int = 6
    n_bins: int = 8
    min_rows: float = 2
    min_gain: float = 0.0
    criterion: str = "gain_ratio"  # "gain" (information gain), "gini"; regression takes variance
    tree: str = "c45"  # one child per bin; "cart": two
    reduction: bool = True
    reduction_scope: str = "tree"  # "shared": one importance for all trees, from all rows
    feature_draw: str = "tree"  # "node": new random features at each node
    sampling: str = "poisson"  # "multinomial": exact draws, stored; "copied": draws as copied rows
    sampling_scope: str = "global"  # "partition": draws made within blocks of rows
    layout: str = "horizontal"  # "vertical": slices; "blocks": packed slices; "auto": the one that sends least
    parallel: str = "both"  # "trees", "features", "none"
    vote: str = "weighted"  # "direct"
    normalise: bool = True
    tree_group: int = 64
    state: str = "memory"  # "disk": every level's state is written and read
    seed: int = 42

    def sized(self, n_features: int) -> ForestSpec:
        """With the numbers of principal and selected features filled in and checked."""
        for name, allowed in CHOICES.items():
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} {getattr(self, name)!r} is none of {', '.join(allowed)}")
        m = self.n_selected or min(n_features, 2 * math.ceil(math.sqrt(n_features)))
        p = self.n_principal if self.n_principal is not None else max(1, math.ceil(m / 2))
        m = min(m, n_features)
        if self.reduction and not (0 < p <= m):
            raise ValueError(f"n_principal {p} must be from 1 to n_selected {m}")
        if self.reduction and p == m and m < n_features:
            warnings.warn("no room for random features: n_principal equals n_selected", stacklevel=2)
        return replace(self, n_selected=m, n_principal=min(p, m), criterion=self.criterion if self.task == "classification" else "gain")

    def but(self, **changes) -> ForestSpec:
        return replace(self, **changes)
