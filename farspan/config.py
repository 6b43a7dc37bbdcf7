"""Settings of a selection run."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Config:
    """L: window length in tokens; k: least distance of a far cell; alpha: weight of the uniformity score."""

    L: int = 32_768
    k: int = 8_192
    alpha: float = 0.5
    token_mode: str = "word"
    profile: str = "hexdot"
    var_over: str = "triangle"
    head_agg: str = "mean"
    ddof: int = 0
    std_scope: str = "global"
    category: str = "lang"
    block: int = 128
    seed: int = 7

    def __post_init__(self):
        if self.L < 1 or self.k < 0:
            raise ValueError("L must be positive and k not negative")

    @classmethod
    def paper(cls) -> Config:
        """The published setting: windows of 32,768 tokens, k a quarter of it, alpha 0.5."""
        return cls()

    @classmethod
    def scaled(cls, L: int, **more) -> Config:
        """The same proportions at another window length."""
        return cls(L=L, k=L // 4, **more)

    def but(self, **more) -> Config:
        return replace(self, **more)
