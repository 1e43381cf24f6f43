"""All parameters of a summary in one validated object."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Params:
    # detection
    rounds: int = 10
    threshold: str | int = "mode"  # 'mode', 'average' or a number
    threshold_scale: int = 1
    schedule: str = "power"  # 'power', 'geometric', 'constant'
    factor: float = 2.0
    carry: str = "contract"  # 'contract', 'labels'
    admit: str = "le"  # 'le', 'lt'
    tie: str = "source"  # 'source', 'hold', 'lower_id'
    stop_when_stable: bool = True
    # sizes
    size_method: str = "sketch"  # 'sketch', 'exact'
    size_by: str = "volume"  # 'volume', 'inner_edges', 'incident_edges', 'nodes'
    depth: int = 4
    width: int | None = None
    width_fraction: float = 1e-3
    min_width: int = 16
    # layout
    iterations: int = 100
    gravity: float = 1.0
    repulsion: float = 80.0
    gravity_mode: str = "unit"  # 'unit', 'strong'
    attraction: str = "linear"  # 'linear', 'unit', 'log'
    speed: str = "published"  # 'published', 'paper'
    tolerance: float = 1.0
    stop_eps: float | None = None
    engine: str = "auto"  # 'auto', 'task', 'blocks', 'spark'
    # drawing
    tail_share: float = 0.5
    bands: str = "equal_count"  # 'equal_count', 'equal_weight', 'log_size'
    seed: int = 0

    def __post_init__(self):
        allowed = {
            "schedule": ("power", "geometric", "constant"), "carry": ("contract", "labels"), "admit": ("le", "lt"), "tie": ("source", "hold", "lower_id"),
            "size_method": ("sketch", "exact"), "size_by": ("volume", "inner_edges", "incident_edges", "nodes"), "gravity_mode": ("unit", "strong"),
            "attraction": ("linear", "unit", "log"), "speed": ("published", "paper"), "engine": ("auto", "task", "blocks", "spark"), "bands": ("equal_count", "equal_weight", "log_size"),
        }
        for name, values in allowed.items():
            if getattr(self, name) not in values:
                raise ValueError(f"{name} must be one of {values}, not {getattr(self, name)!r}")
        if isinstance(self.threshold, str) and self.threshold not in ("mode", "average"):
            raise ValueError("threshold must be 'mode', 'average' or a number")
        for name in ("rounds", "depth", "threshold_scale", "min_width"):
            if getattr(self, name) < 1:
                raise ValueError(f"{name} must be at least 1")
        if self.iterations < 0 or not 0 <= self.tail_share <= 1 or self.factor <= 1:
            raise ValueError("iterations, tail_share or factor out of range")
