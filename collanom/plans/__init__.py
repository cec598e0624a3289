"""Choosing a plan, and running it in stages that survive lost executors."""

from .planner import Plan, choose, explain_plan
from .stages import detect_table, materialised

__all__ = ["Plan", "choose", "detect_table", "explain_plan", "materialised"]
