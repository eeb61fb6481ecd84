"""Reasoning on the driver: dependencies, their order, and the plan of a repair."""

from .fd import FD, parse
from .repair_plan import RepairPlan, build_plan

__all__ = ["FD", "RepairPlan", "build_plan", "parse"]
