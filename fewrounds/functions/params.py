"""Parameters of the few-round methods, with floors for small graphs."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Params:
    n: int
    log_floor: float  # lg lg n, at least 2
    s: int  # degree that makes a component awake
    p_edge: float
    p_leader: float
    num_samples: int
    small: float  # size of a small component, sqrt(lg n)
    seed: int = 0
    faithful: bool = True


def params_for(n: int, faithful: bool = True, **overrides) -> Params:
    """Values for n vertices: the method's own, with sqrt(n) samples.  ``faithful=False`` takes 16 at most, which saves
    rows in the samples for more work in the finisher and never changes answers."""
    lg = math.log2(max(n, 2))
    floor = max(2.0, math.log2(max(lg, 2)))
    m = max(1, math.ceil(math.sqrt(max(n, 1))))
    base = Params(n, floor, max(2, math.ceil(floor)), 1 / floor, 1 / floor, m if faithful else min(m, 16), math.sqrt(lg), faithful=faithful)
    return replace(base, **overrides)
