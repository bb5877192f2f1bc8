"""Settings of the engine. No published value exists for any of them; the defaults were measured on the given tables."""

from __future__ import annotations

import math
from dataclasses import dataclass, field, replace


@dataclass(frozen=True)
class Config:
    """Bits kept, bits a term, further groupings, least shared terms, candidates a query, and the largest accepted distance."""

    bits: int = 256
    width: int = 12
    repeats: int = 2
    min_overlap: int = 1
    k: int = 100
    max_distance: int = 64
    augment_k: int = 2
    seed: int = 0
    head_rule: str = "seeded"
    merge: str = "follow"
    #: Distance at which a pair is found with probability ``found`` or more.
    design_distance: int = 48
    found: float = 0.99
    #: Largest accepted distance of each application: feeds take medium precision, removal and metadata high.
    application: dict = field(default_factory=lambda: {"feed": 80, "metadata": 48, "copyright": 32, "canonical": 64})

    @property
    def threshold(self) -> float:
        """The score between those of ``max_distance`` and of one more differing bit."""
        return 1 - (self.max_distance + 0.5) / self.bits

    def for_items(self, n: int) -> Config:
        """The layout for ``n`` items: terms so wide that a random posting list holds about one, and as many groupings as
        find the pairs at the design distance. The default layout is that of up to 4,096 items.
        """
        width = max(12, math.ceil(math.log2(max(2, n))))
        both = (1 - self.design_distance / self.bits) ** width
        groups = math.ceil(math.log(1 - self.found) / math.log(1 - both))
        return replace(self, width=width, repeats=max(0, math.ceil(groups / (self.bits // width)) - 1))


DEFAULT = Config()
