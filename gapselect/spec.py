"""What a selection problem is made of: features in bit order, subgroups, target."""

from __future__ import annotations

from dataclasses import dataclass

MAX_FEATURES, MAX_STATES, PER_WORD = 30, 9, 15


@dataclass(frozen=True)
class FeatureSpec:
    """Candidate features (position = bit), the subgroup column and the target column."""

    features: tuple[str, ...]
    group: str = "sg"
    target: str = "y"

    def __post_init__(self):
        if not self.features or len(set(self.features)) < len(self.features):
            raise ValueError("features must be given and differ")
        if len(self.features) > MAX_FEATURES:
            raise ValueError(f"at most {MAX_FEATURES} features fit the packed code, got {len(self.features)}")
        if self.group in self.features:
            raise ValueError("a grouping feature cannot be a candidate")
        if self.target in self.features:
            raise ValueError("the target cannot be a candidate")

    @property
    def n(self) -> int:
        return len(self.features)

    def mask_of(self, names) -> int:
        return sum(1 << self.features.index(x) for x in names)

    def names_of(self, mask: int) -> list[str]:
        return [f for j, f in enumerate(self.features) if mask >> j & 1]

    def head(self, n: int) -> FeatureSpec:
        return FeatureSpec(self.features[:n], self.group, self.target)


def check_request(spec: FeatureSpec, m: int, k: int) -> None:
    if not 1 <= m <= spec.n:
        raise ValueError(f"set size {m} is not within 1..{spec.n}")
    if k < 1:
        raise ValueError("K must be at least 1")


def widen(mask: int) -> tuple[int, int]:
    """Nibble masks of the two packed words."""
    words = [0, 0]
    for j in range(MAX_FEATURES):
        if mask >> j & 1:
            words[j // PER_WORD] |= 0xF << 4 * (j % PER_WORD)
    return words[0], words[1]


def band(n: int, low: int, high: int, within: int | None = None) -> list[int]:
    """Masks of ``low..high`` features, ascending; only bits of ``within`` if given."""
    if low > high:
        raise ValueError("level_min exceeds level_max")
    from itertools import combinations

    bits = [j for j in range(n) if within is None or within >> j & 1]
    return sorted(sum(1 << j for j in c) for level in range(max(1, low), min(high, len(bits)) + 1) for c in combinations(bits, level))
