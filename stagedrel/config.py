"""Published settings as defaults, and our own where none are published (marked)."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class SftConfig:
    fraction: float = 0.25
    epochs: int = 20
    per_worker: int = 8
    workers: int = 8
    accumulation: int = 2
    lr: float = 1e-4
    warmup: float = 0.05
    max_tokens: int = 2096


@dataclass(frozen=True)
class RlConfig:
    epochs: int = 4
    alpha: float = 0.5
    per_worker: int = 16
    workers: int = 8
    accumulation: int = 1
    lr: float = 1e-6
    warmup: float = 0.05
    temperature: float = 0.8
    max_tokens: int = 1024
    eps: float = 0.2
    beta: float = 0.001
    mu: int = 2
    length_threshold: int = 1024
    k: int = 8  # own choice: the group size is not published
    reward_weights: tuple[float, float, float] = (1.0, 1.0, 1.0)
    ddof: int = 0


@dataclass(frozen=True)
class EngineLr:
    """Learning rates of the in-engine policy; the published ones are for a model of billions of weights."""

    sft: float = 0.05
    rl: float = 1.0


@dataclass(frozen=True)
class Config:
    seed: int = 42
    sft: SftConfig = field(default_factory=SftConfig)
    rl: RlConfig = field(default_factory=RlConfig)
    engine: EngineLr = field(default_factory=EngineLr)


def effective_batch(cfg: SftConfig | RlConfig) -> int:
    return cfg.per_worker * cfg.workers * cfg.accumulation
