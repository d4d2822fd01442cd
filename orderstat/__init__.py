"""Exact multiple selection on Spark: order statistics at given ranks without sorting what need not be sorted."""

from orderstat.operators.engine import Ledger, multi_select
from orderstat.plans.policy import Branch, Settings, TallCache, choose_branch

__all__ = ["Branch", "Ledger", "Settings", "TallCache", "choose_branch", "multi_select"]
