"""Parameters of an index, and thresholds derived from them exactly."""

from __future__ import annotations

import json
import math
from dataclasses import asdict, dataclass
from fractions import Fraction

#: Modulus of the universal hash family and the stated universe (fixed values).
PRIME = 2**31 - 1
UNIVERSE = 2**32


@dataclass(frozen=True)
class HashParams:
    """``bin_space='range'`` cuts the hash range [0, PRIME) into bins; ``'universe'`` cuts the
    stated universe, whose upper half no hash value reaches."""

    char_lens: tuple[int, ...] | str = (1, 3, 5)
    bins: int = 4
    repetitions: int = 20
    alpha: str = "0.2"
    bin_space: str = "range"
    scheme: str = "oph"  # or "kperm": one permutation a bin
    densify: str = "coin"  # or "left", "right", "coin_offset"
    fingerprint: str = "md5_32"  # or "crc32", "xxhash64"
    width: int = 31  # or 62: two chained folds
    seed: int = 7

    @property
    def index_min(self) -> int:
        """Least weight an edge needs to stay: ceil(alpha T), one at least."""
        return max(1, math.ceil(Fraction(self.alpha) * self.repetitions))

    def infer_min(self, inclusive: bool = False) -> int:
        """Least weight an unseen word needs: above alpha T, or from it on if inclusive."""
        return self.index_min if inclusive else math.floor(Fraction(self.alpha) * self.repetitions) + 1

    @property
    def space(self) -> int:
        return PRIME if self.bin_space == "range" else UNIVERSE

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    @staticmethod
    def from_json(text: str) -> HashParams:
        raw = json.loads(text)
        if isinstance(raw["char_lens"], list):
            raw["char_lens"] = tuple(raw["char_lens"])
        return HashParams(**raw)
