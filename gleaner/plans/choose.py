"""Which form of each step runs, from sizes known before."""

from __future__ import annotations

from dataclasses import dataclass

from gleaner.operators.lengths import LengthUtility


@dataclass(frozen=True)
class Choice:
    """``weight`` is what ``model.weights`` does for the length function; ``pick`` and ``engine`` are what the sampler runs."""

    weight: str
    pick: str
    engine: str

    def text(self) -> str:
        return "\n".join(f"{k}: {v}" for k, v in vars(self).items())


def choose(k: int, n_max: int, transactions: int, f: LengthUtility) -> Choice:
    """A race only for very few draws from little; nested expressions while they are short, then arrays in Arrow with
    logarithms of masses, and long rows where a transaction is too long for an array."""
    weight = "closed form" if f.closed else "table of sizes"
    pick = "race" if k * transactions <= 10_000 else "prefix"
    engine = "sql" if n_max <= 60 else "arrow" if n_max <= 1_000_000 else "long"
    return Choice(weight, pick, engine)
