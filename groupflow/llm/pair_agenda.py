"""Merging of adjacent symbols by score, for many short words at once.

The agenda of a word is a row of a matrix: the rank of each adjacent pair that is a piece. In each round
every row joins its best pair, the leftmost among equals, and ranks the two pairs that are new.
Symbols are numbers; a hash table in an array gives the piece that two of them join to.
"""

from __future__ import annotations

import numpy as np

_NONE = np.int32(2**31 - 1)
_HASH = np.uint64(0x9E3779B97F4A7C15)


class PairAgenda:
    """Merge rules of a vocabulary ``piece -> (id, rank)``; a smaller rank is joined first."""

    def __init__(self, ids: dict[str, int], ranks: dict[str, int]):
        self.ids = ids
        top = max(ids.values(), default=0) + 1
        known = dict(ids)
        for piece in ids:
            for c in piece:
                if c not in known:
                    known[c] = top  # a character that is no piece of its own, but part of some
                    top += 1
        self.known, self.first_unknown = known, top
        self.known_text = {i: c for c, i in known.items()}
        self.bmp = np.arange(top, top + 65536, dtype=np.int64)
        self.far: dict[int, int] = {}
        for c, i in known.items():
            if len(c) == 1:
                if ord(c) < 65536:
                    self.bmp[ord(c)] = i
                else:
                    self.far[ord(c)] = i
        rank_of = np.full(top, _NONE, np.int32)
        pairs: dict[int, int] = {}
        for piece, i in ids.items():
            rank_of[i] = ranks[piece]
            for cut in range(1, len(piece)):
                a, b = known.get(piece[:cut]), known.get(piece[cut:])
                if a is not None and b is not None:
                    pairs[a << 32 | b] = i
        self.rank_of = rank_of
        keys = np.fromiter(pairs, np.uint64, len(pairs))
        values = np.fromiter(pairs.values(), np.int64, len(pairs))
        self.bits = max(4, (8 * len(pairs)).bit_length())
        self.keys = np.full((1 << self.bits) + 64, 2**64 - 1, np.uint64)
        self.values = np.zeros(len(self.keys), np.int64)
        self.probes = 1
        for key, value, at in zip(keys, values, self._slot(keys).tolist()):
            steps = 1
            while self.keys[at] != np.uint64(2**64 - 1):
                at += 1
                steps += 1
            self.keys[at], self.values[at] = key, value
            self.probes = max(self.probes, steps)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * _HASH) >> np.uint64(64 - self.bits)).astype(np.int64)

    def joined(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The pieces that symbols join to, and their ranks; rank ``_NONE`` where they join to none."""
        keys = a.astype(np.uint64) << np.uint64(32) | b.astype(np.uint64)
        slot = self._slot(keys)
        piece = np.full(len(keys), -1, np.int64)
        left = np.arange(len(keys))
        for step in range(self.probes):
            there = self.keys[slot[left] + step]
            hit = there == keys[left]
            piece[left[hit]] = self.values[slot[left[hit]] + step]
            left = left[~hit & (there != np.uint64(2**64 - 1))]
            if not len(left):
                break
        return piece, np.where(piece >= 0, self.rank_of[piece], _NONE)

    def symbols(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Numbers of the words' characters one after another, and the words' lengths."""
        codes = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32)
        out = self.bmp[np.minimum(codes, 65535)]
        for at in np.flatnonzero(codes > 65535).tolist():
            code = int(codes[at])
            out[at] = self.far.get(code, self.first_unknown + code)
        return out, np.fromiter(map(len, words), np.int64, len(words))

    def merge(self, words: list[str]) -> list[tuple[int, ...]]:
        """Symbols of each word when no pair is left to join; unknown characters are above all ids."""
        out: list[tuple[int, ...]] = [()] * len(words)
        flat, lengths = self.symbols(words)
        begins = np.cumsum(lengths) - lengths
        order = np.argsort(lengths, kind="stable")
        for at in range(0, len(order), 4096):
            rows = order[at : at + 4096]
            size = lengths[rows]
            width = int(size[-1]) if len(size) else 0
            if not width:
                continue
            where = begins[rows][:, None] + np.arange(width)
            inside = np.arange(width) < size[:, None]
            sym = np.where(inside, flat[np.minimum(where, len(flat) - 1)], -1)
            done = self._rounds(sym, size.copy())
            symbols, left = done
            values = symbols[np.arange(width) < left[:, None]].tolist()
            ends = np.cumsum(left).tolist()
            for row, a, b in zip(rows.tolist(), [0, *ends], ends):
                out[row] = tuple(values[a:b])
        return out

    def _rounds(self, sym: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n, width = sym.shape
        result, sizes = sym.copy(), size.copy()
        if width < 2:
            return result, sizes
        rank = np.full((n, width), _NONE, np.int32)
        piece = np.full((n, width), -1, np.int64)
        r, c = np.nonzero(np.arange(width - 1) < size[:, None] - 1)
        piece[r, c], rank[r, c] = self.joined(sym[r, c], sym[r, c + 1])
        rows = np.arange(n)
        columns = np.arange(width)
        while True:
            best = rank.argmin(axis=1)
            local = np.arange(len(rows))
            live = rank[local, best] < _NONE
            if not live.all():
                result[rows[~live]], sizes[rows[~live]] = sym[~live], size[~live]
                rows, sym, size, rank, piece, best = rows[live], sym[live], size[live], rank[live], piece[live], best[live]
                local = np.arange(len(rows))
            if not len(rows):
                return result, sizes
            sym[local, best] = piece[local, best]
            # what stands right of the joined pair moves one place to the left
            source = columns + (columns > best[:, None])
            source[:, -1] = np.minimum(source[:, -1], width - 1)
            sym = np.take_along_axis(sym, source, axis=1)
            source = columns + (columns >= best[:, None])
            source[:, -1] = width - 1
            rank = np.take_along_axis(rank, source, axis=1)
            piece = np.take_along_axis(piece, source, axis=1)
            size = size - 1
            rank[local, size - 1], rank[:, -1] = _NONE, _NONE
            has = best < size - 1
            i, at = local[has], best[has]
            piece[i, at], rank[i, at] = self.joined(sym[i, at], sym[i, at + 1])
            has = best > 0
            i, at = local[has], best[has] - 1
            piece[i, at], rank[i, at] = self.joined(sym[i, at], sym[i, at + 1])
