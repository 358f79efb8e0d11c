"""Cost presets: model sizes and hardware."""

from __future__ import annotations

from dataclasses import dataclass

from adapterlab.simulate.pipeline import PipeConfig


@dataclass(frozen=True)
class Preset:
    name: str
    stages: int
    capacity: int
    per_token: float
    last_extra: float


MODELS = {
    "small": Preset("small", 1, 8192, 1.0, 0.0),
    "medium": Preset("medium", 2, 4096, 4.0, 0.05),
    "medium_four": Preset("medium_four", 4, 4096, 2.0, 0.05),  # the same layers over four devices
    "large": Preset("large", 4, 4096, 9.0, 0.05),
}
# Less memory and slower links: half the capacity, dearer tokens.
HARDWARE = {"first": (1.0, 1.0), "second": (0.5, 2.6)}


def pipe_config(preset: Preset, factor: float, hardware: str = "first") -> PipeConfig:
    """factor: time per token relative to the frozen layer, by the traffic ledger (`kernel_factors`)."""
    return PipeConfig(preset.stages, 0.0, preset.per_token * factor * HARDWARE[hardware][1], 2.0, preset.last_extra)
