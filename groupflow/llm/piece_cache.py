"""A bounded cache of encoded pieces: two generations behind a doorkeeper."""

from __future__ import annotations

from collections.abc import Callable, Iterable

_DOOR = (1 << 23) - 1


class PieceCache(dict):
    """Encodings of at most ``2 * limit`` pieces, and of those of the batch at hand.

    A piece is kept from its second batch on (a bitmap of hashes remembers the first), since most
    new pieces never come back. When the young generation is full it becomes the old one; pieces met
    again are carried over. A worker process keeps its cache from task to task. The cache only
    saves time and never changes a result.
    """

    def __init__(self, limit: int):
        super().__init__()
        self.limit, self.old, self.passing = limit, {}, {}
        self.door = bytearray(_DOOR + 1)

    def missing(self, pieces: Iterable[str]) -> list[str]:
        """The pieces of a batch that are to be encoded and given to :meth:`learn`."""
        if len(self) > self.limit:
            self.old = dict(self)
            self.clear()
            self.door = bytearray(_DOOR + 1)
        fresh = set(pieces).difference(self)
        if self.old:
            back = fresh & self.old.keys()
            self.update((p, self.old[p]) for p in back)
            fresh -= back
        self.passing = {}
        return list(fresh)

    def learn(self, pieces: Iterable[str], values: Iterable) -> None:
        """Encodings of missing pieces; from here on each piece of the batch can be looked up."""
        door, passing = self.door, self.passing
        for piece, value in zip(pieces, values):
            at = hash(piece) & _DOOR
            if door[at]:
                self[piece] = value
            else:
                door[at] = 1
                passing[piece] = value

    def __missing__(self, piece: str):
        return self.passing[piece]


class LazyCache(dict):
    """Encodings looked up by ``cache[piece]``; a missing one is encoded there and then.

    Bounded like :class:`PieceCache`: a piece is kept from its second miss on, in two generations.
    """

    def __init__(self, limit: int, encode: Callable[[str], bytes]):
        super().__init__()
        self.limit, self.encode, self.old = limit, encode, {}
        self.door = bytearray(_DOOR + 1)

    def __missing__(self, piece: str) -> bytes:
        value = self.old.get(piece)
        if value is None:
            value = self.encode(piece)
            at = hash(piece) & _DOOR
            if not self.door[at]:
                self.door[at] = 1
                return value
        if len(self) >= self.limit:
            self.old = dict(self)
            self.clear()
            self.door = bytearray(_DOOR + 1)
        self[piece] = value
        return value
