"""Deterministic label-exchange connectivity for very large graphs on Spark."""

from starfold.operators.alternating import connected_components
from starfold.plans.loop import ComponentResult

__all__ = ["ComponentResult", "connected_components"]
