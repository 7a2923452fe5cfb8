"""Imports every module that registers queries."""

from blockflow.plans import ablations, aliases, baselines, corpus, graph, release, streams, surface  # noqa: F401
from blockflow.plans.base import ORACLES, QUERIES  # noqa: F401
