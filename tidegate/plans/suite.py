"""Imports every module that registers queries."""

from tidegate.plans import suite_gate, suite_measures, suite_merge, suite_relational, suite_runs, suite_sizing, suite_streams  # noqa: F401
