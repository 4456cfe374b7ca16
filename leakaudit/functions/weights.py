"""Weight schemes: what a character of each kind counts."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

#: The final token weights.
DEFAULT = {"boilerplate": 0.1, "standard": 1.0, "long": 3.0, "literal": 5.0, "lint": 5.0, "comment": 10.0, "slippage": 10.0, "tag": 10.0}


@dataclass(frozen=True)
class Scheme:
    """Weights by kind; a kind that is absent has no part. ``tag`` overrides what it covers, the others compete by maximum."""

    weights: dict[str, float] = field(default_factory=lambda: dict(DEFAULT))
    long_min: int = 10

    @classmethod
    def default(cls) -> Scheme:
        return cls()

    @classmethod
    def uniform(cls) -> Scheme:
        return cls(dict.fromkeys(DEFAULT, 1.0))

    def without(self, kind: str) -> Scheme:
        """The scheme with one signal off; without identifiers' own kinds they count as standard."""
        return replace(self, weights={k: w for k, w in self.weights.items() if k != kind})

    def only(self, *kinds: str) -> Scheme:
        return replace(self, weights={k: w for k, w in self.weights.items() if k in kinds or k in ("boilerplate", "standard")})

    def __getitem__(self, kind: str) -> float:
        return self.weights.get(kind, 0.0)
