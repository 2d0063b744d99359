"""Encoded pieces of texts, remembered within bounds."""

from __future__ import annotations

from collections.abc import Callable


class Memo:
    """Maps pieces to bytes, making each missing one once for a batch.

    Two generations bound the memory: when the younger is full it becomes the
    older and the older goes, so pieces in use stay and rare ones leave.
    """

    def __init__(self, make: Callable[[list], list[bytes]], most: int):
        self.make, self.most = make, most
        self.young: dict[str | bytes, bytes] = {}
        self.old: dict[str | bytes, bytes] = {}

    def _know(self, pieces: set) -> dict:
        """The younger generation, once it holds all of ``pieces``."""
        if len(self.young) > self.most:
            self.old, self.young = self.young, {}
        missing = pieces.difference(self.young)
        if self.old and missing:
            old = self.old
            kept = {p: old[p] for p in missing if p in old}
            self.young.update(kept)
            missing = missing.difference(kept)
        if missing:
            fresh = list(missing)
            self.young.update(zip(fresh, self.make(fresh), strict=True))
        return self.young

    def each(self, pieces: list) -> list[bytes]:
        """The bytes of each piece."""
        return list(map(self._know(set(pieces)).__getitem__, pieces))

    def joined(self, texts: list[list]) -> list[bytes]:
        """The bytes of each text's pieces, joined."""
        known = self._know(set().union(*texts))
        return [b"".join(map(known.__getitem__, t)) for t in texts]
