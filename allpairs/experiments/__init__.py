"""The experiments: each runner gives rows of what was varied, what came out and how long it took."""

from .runners import EXPERIMENTS

__all__ = ["EXPERIMENTS"]
