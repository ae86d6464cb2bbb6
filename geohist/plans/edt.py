"""The even-density tree from points to published leaves."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame

from geohist.functions import noise
from geohist.functions.budget import Budget, Ledger, levels
from geohist.operators import grid, release, tree
from geohist.operators.release import StopRule
from geohist.sources import sinks


@dataclass(frozen=True)
class TreePlan:
    """How a tree is built: search rounds, split method, axis rule, height (None: estimated), mode and secret."""

    rounds: int = 3
    split: str = "searched"
    axis_rule: str = "even_x"
    height: int | None = None
    c0: float = 10.0
    allow_no_split: bool = False
    mode: str = "auto"
    release: str = "pruned"
    allocation: str = "geo"
    secret: str | None = field(default=None, repr=False)


#: Ablations: what they change in the plan or the stop rule.
VARIANTS: dict[str, dict] = {
    "searched": {},
    "exhaustive": {"split": "exhaustive"},
    "exponential": {"split": "exponential_unevenness"},
    "median": {"split": "em_median"},
    "mean": {"split": "noisy_mean"},
    "midpoint": {"split": "midpoint"},
    "leaves_only": {"release": "leaves"},
    "all_nodes": {"release": "all"},
    "uniform_levels": {"allocation": "uniform"},
    "no_stop": {},
}


@dataclass
class Release:
    """Nodes (exact counts: curator only), published leaves, ledger, height, and the secret of its noise (curator only)."""

    nodes: DataFrame
    published: DataFrame
    ledger: Ledger
    height: int
    secret: str = field(repr=False)

    def write(self, path: str, fmt: str = "parquet", testing: bool = False) -> None:
        """Published leaves and ledger, nothing else; refused if the noise is drawn with the published test key."""
        sinks.write(self.published, self.ledger.frame(self.published.sparkSession), path, self.secret, fmt, testing)


def publish_matrix(fm: DataFrame, spec: grid.GridSpec, budget: Budget, plan: TreePlan = TreePlan(), stop: StopRule = StopRule(), tree_id: str = "edt", variant: str = "searched") -> Release:
    """Height estimate, partition and release of a frequency matrix, with a ledger that is checked against the total."""
    noise.held(plan.secret)
    plan = replace(plan, **VARIANTS[variant])
    if variant == "no_stop":
        stop = StopRule(None, None)
    ledger = Ledger()
    if plan.height is None:
        h = tree.noisy_height(fm, budget.eps_height, budget.eps_tot, plan.secret, tree_id, plan.c0, spec.cells)
        ledger.spend("height", budget.eps_height, tree_id=tree_id)
    else:
        h = plan.height
    eps_data = budget.data(h)
    for i in range(h, 0, -1):
        ledger.spend("split", budget.level(h), "disjoint", i, tree_id)
    nodes = tree.build(fm, spec, h, plan.split, budget.level(h) if h else 0.0, plan.secret, tree_id, plan.rounds, plan.axis_rule, plan.allow_no_split, plan.mode)
    if plan.release == "leaves":
        out = release.leaves_only(nodes, eps_data, plan.secret)
    elif plan.release == "all":
        out = tree.leaves(release.all_nodes(nodes, levels(eps_data, h, plan.allocation), plan.secret))
    else:
        out = release.pruned(nodes, h, eps_data, stop, plan.allocation, secret=plan.secret)
    ledger.spend("data", eps_data, tree_id=tree_id)
    ledger.check(budget.eps_tot)
    return Release(nodes, release.redact(out), ledger, h, plan.secret)


def publish(points: DataFrame, spec: grid.GridSpec, budget: Budget, plan: TreePlan = TreePlan(), stop: StopRule = StopRule(), tree_id: str = "edt", variant: str = "searched") -> Release:
    """From points: one pass over them makes the matrix, written once and used by every later step."""
    return publish_matrix(tree.stored(grid.frequency_matrix(points, spec)), spec, budget, plan, stop, tree_id, variant)
