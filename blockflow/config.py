"""Options of the feature and similarity pipeline."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class FeatureConfig:
    """representation numeric or string; shape centroid, xy or xyz; metric hybrid, cosine, gauss or cls."""

    representation: str = "numeric"
    shape: str = "xy"
    semantic: bool = True
    size_weight: bool = True
    metric: str = "hybrid"
    gamma: float = 5.0
    rounds: int = 1
    x_offset: float = 0.0
    layout: str = "concat"
    #: Order of a sample's nodes in the concat layout: func_id or content.
    node_order: str = "func_id"
    #: Vectors of different lengths: pad with zeros, or never match.
    lengths: str = "pad"
    neighbours: str = "out"
    hop_agg: str = "sum"
    ignore_weight: float = 1.0


#: Duplicate cuts of samples and of functions.
SAMPLE_TAU, FUNCTION_TAU = 0.9999, 0.999
