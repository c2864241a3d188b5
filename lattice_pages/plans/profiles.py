"""Profiles: the bounded sets of choices an encoder may make, and the ablations of them."""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np

PAGE = 1024
DOMAINS = ("binary64", "binary32", "integer")


@dataclass(frozen=True)
class Profile:
    name: str
    max_lanes: int
    block: int = 16
    upper: bool = False  # predictors, split, Rice and residual divisors per block
    bounded: bool = False
    eps: float | None = None
    use_affine: bool = False
    use_predictors: bool = False
    use_split: bool = False
    use_rice: bool = False
    use_gcd: bool = False
    persist: bool = True  # a lane keeps its history across route changes
    predict: bool = True  # else every value is taken against the lane's anchor
    factor: bool = True  # bounded: store q / d, not q
    learn_width: bool = True
    alpha: float = 0.0  # a lane must save more than (1 + alpha) times its overhead
    zstd: int = 3  # of a page group's metadata, or of all of it for upper
    domain: str = "binary64"  # what a word is: binary64, binary32 (low 32 bits) or integer

    def __post_init__(self) -> None:
        if self.domain not in DOMAINS or (self.bounded and self.domain == "integer"):
            raise ValueError("the domain is binary64, binary32 or, for exact profiles, integer")
        if not 0 <= self.max_lanes <= 4 or self.block < 1:
            raise ValueError("a page has at most four lanes, and blocks of one value or more")

    @property
    def contract(self) -> str:
        return ("bounded" if self.bounded else "exact") + {"binary64": "", "binary32": "32", "integer": "_integer"}[self.domain]

    @property
    def word_bytes(self) -> int:
        return 4 if self.domain == "binary32" else 8

    def values(self, words: np.ndarray) -> np.ndarray:
        """The words as doubles (integers are converted, which only statistics and errors use)."""
        if self.domain == "binary64":
            return words.view(np.float64)
        return words.astype(np.float64) if self.domain == "integer" else words.astype(np.uint32).view(np.float32).astype(np.float64)


EXACT_FAST = Profile("exact_fast", 3)
EXACT_UPPER = Profile("exact_upper", 4, upper=True, use_affine=True, use_predictors=True, use_split=True, use_rice=True, use_gcd=True, zstd=22)
BOUNDED = Profile("bounded", 3, bounded=True, eps=1e-3)
MAX_LANES = {p.name: p.max_lanes for p in (EXACT_FAST, EXACT_UPPER, BOUNDED)}

#: Ablations by name: the profile with one mechanism removed.
ABLATIONS: dict[str, Profile] = {
    "no_prediction": replace(EXACT_FAST, predict=False),
    "one_lane": replace(EXACT_FAST, max_lanes=1),
    "reset_state": replace(EXACT_FAST, persist=False),
    "no_upper": EXACT_FAST,
    "no_affine_resgcd": replace(EXACT_UPPER, use_affine=False, use_gcd=False),
    "no_resgcd": replace(EXACT_UPPER, use_gcd=False),
    "no_split": replace(EXACT_UPPER, use_split=False),
    "no_rice": replace(EXACT_UPPER, use_rice=False),
    "bounded_one_lane": replace(BOUNDED, max_lanes=1, factor=False),
    "bounded_no_factor": replace(BOUNDED, factor=False),
}


def profile(name: str | Profile, eps: float | None = None, **overrides) -> Profile:
    got = name if isinstance(name, Profile) else {p.name: p for p in (EXACT_FAST, EXACT_UPPER, BOUNDED)}.get(name) or ABLATIONS[name]
    if eps is not None:
        overrides["eps"] = eps
    return replace(got, **overrides) if overrides else got
