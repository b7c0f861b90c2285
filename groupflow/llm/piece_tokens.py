"""SentencePiece encoding of merge-type vocabularies, by an agenda of adjacent pairs.

Symbols start as characters. An agenda holds every adjacent pair whose concatenation is a piece, the
best score first and the leftmost first among equals; pairs are joined until the agenda is empty,
then symbols outside the vocabulary fall back to bytes. Texts are cut into units where no piece
can reach across, so the agenda of a unit decides alone and its ids can be kept. The agendas of the
units that are new in a batch are worked off together, and the batch's units are compared with
the sentencepiece library.
"""

from __future__ import annotations

import hashlib
import heapq
import re
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain
from operator import add

import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupflow.llm.pair_agenda import PairAgenda
from groupflow.llm.piece_cache import PieceCache
from groupflow.llm.worker_memory import tidy

_SPACE = "▁"
# units of more characters go to the heap
_SHORT = 48
_BITS = 32
_POSITION = (1 << _BITS) - 1


class AgendaEncoder:
    """The encoder of one model file; raises where the model is of a kind it does not cover."""

    def __init__(self, path: str, cached: int = 450_000):
        self.library = lib = sentencepiece.SentencePieceProcessor(model_file=path)
        scores: dict[str, float] = {}
        self.ids: dict[str, int] = {}
        self.bytes: list[int | None] = [None] * 256
        self.unknown = lib.unk_id()
        for i in range(lib.vocab_size()):
            piece = lib.id_to_piece(i)
            if lib.is_byte(i):
                self.bytes[int(piece[3:5], 16)] = i
            elif not (lib.is_control(i) or lib.is_unknown(i)):
                if lib.is_unused(i):
                    raise ValueError("unused pieces are not covered")
                scores[piece], self.ids[piece] = lib.get_score(i), i
                if _SPACE in piece.lstrip(_SPACE):
                    raise ValueError("a piece reaches over the start of a word")
        probe = "  a ﬁ A"
        if None in self.bytes or lib.normalize(probe) != _SPACE + probe.replace(" ", _SPACE):
            raise ValueError("only byte fallback, no normalisation and a dummy prefix are covered")
        levels = {score: i for i, score in enumerate(sorted(set(scores.values()), reverse=True))}
        self.ranks = {piece: levels[score] for piece, score in scores.items()}
        self.agenda = PairAgenda(self.ids, self.ranks)
        self.pseudo = lib.vocab_size()
        self.neighbours = {piece[i : i + 2] for piece in scores for i in range(len(piece) - 1)}
        self.alone = {c: len(lib.encode(c)) for c in "\na"}
        self.cutter = self._cutter()
        self.known = PieceCache(cached)

    def merge(self, unit: str) -> tuple[int, ...]:
        """Ids of one unit, by a heap; for units too long for the matrix."""
        symbols = list(unit)
        n = len(symbols)
        rank = self.ranks.get
        # an entry is rank and left position in one number, so the heap compares integers
        agenda = [r << _BITS | i for i, pair in enumerate(map(add, symbols, symbols[1:])) if (r := rank(pair)) is not None]
        heapq.heapify(agenda)
        after = list(range(1, n + 1))
        before = list(range(-1, n - 1))
        while agenda:
            entry = heapq.heappop(agenda)
            i = entry & _POSITION
            j = after[i]
            if j >= n or not symbols[i]:
                continue
            pair = symbols[i] + symbols[j]
            if rank(pair) != entry >> _BITS:
                continue  # one of the two has been joined with another since
            symbols[i], symbols[j] = pair, ""
            after[i] = k = after[j]
            if k < n:
                before[k] = i
                if (r := rank(pair + symbols[k])) is not None:
                    heapq.heappush(agenda, r << _BITS | i)
            h = before[i]
            if h >= 0 and (r := rank(symbols[h] + pair)) is not None:
                heapq.heappush(agenda, r << _BITS | h)
        return tuple(chain.from_iterable(map(self._ids, filter(None, symbols))))

    def _ids(self, symbol: str) -> list[int]:
        i = self.ids.get(symbol)
        return [i] if i is not None else [self.bytes[b] for b in symbol.encode("utf-8", "replace")]

    def merge_all(self, units: list[str]) -> list[tuple[int, ...]]:
        """Ids of many units: short ones in the agenda matrix, long ones by the heap."""
        short = [u for u in units if len(u) <= _SHORT]
        merged = self.agenda.merge(short)
        for n, symbols in enumerate(merged):
            if max(symbols) >= self.pseudo:
                merged[n] = tuple(chain.from_iterable((s,) if s < self.pseudo else self._ids(self._text(s)) for s in symbols))
        if len(short) == len(units):
            return merged
        found = iter(merged)
        return [next(found) if len(u) <= _SHORT else self.merge(u) for u in units]

    def _text(self, symbol: int) -> str:
        """The character of a symbol that is no piece."""
        top = self.agenda.first_unknown
        return self.agenda.known_text[symbol] if symbol < top else chr(symbol - top)

    def _cutter(self) -> re.Pattern:
        """Units of a text with marked spaces.

        A unit ends before a mark of a space. Words and marks are units of their own where no piece holds a
        letter and such a mark side by side, for then no pair joins across.
        """
        marks = {c for piece in self.ids for c in piece if not (c.isalnum() or c in f"_{_SPACE}")} | set("\n\t\r")
        beside = {c for pair in self.neighbours if any(map(str.isalpha, pair)) for c in pair}
        marks = "".join(map(re.escape, sorted(marks - beside)))
        word, end = r"[^\W\d_]", rf"(?=[{_SPACE}{marks}]|\Z)"
        return re.compile(
            rf"{_SPACE}*{word}+{end}|(?<={word})[{marks}]+(?={word}|{_SPACE}|\Z)|{_SPACE}*[^{_SPACE}]+|{_SPACE}+"
        )

    def units(self, text: str) -> list[str]:
        """Units of a whole text."""
        return self.cutter.findall(_SPACE + text.replace(" ", _SPACE)) if text else []

    def learn(self, texts: list[list[str]]) -> None:
        """Encode the units that are new, and compare them with the library.

        The library puts a mark of a space before what it encodes. A unit without one is shown to it after a
        character that no pair joins with it, and what that gives alone is taken off.
        """
        fresh = self.known.missing(chain.from_iterable(texts))
        ours = self.merge_all(fresh)
        shown, skipped = [], []
        for unit in fresh:
            if unit[0] == _SPACE:
                shown.append(unit[1:])
                skipped.append(0)
            else:
                before = "\n" if unit[0].isalpha() else "a"
                shown.append(before + unit)
                skipped.append(self.alone[before])
        theirs = self.library.encode(shown, num_threads=1)
        for unit, ids, expected, skip in zip(fresh, ours, theirs, skipped):
            if list(ids) != (expected[skip:] if skip else expected) and unit != _SPACE:
                raise AssertionError(f"the library encodes {unit!r} otherwise")
        self.known.learn(fresh, ours)

    def encode(self, texts: list[str]) -> list[list[int]]:
        """Ids of whole texts, without begin or end ids."""
        cut = [self.units(t) for t in texts]
        self.learn(cut)
        get = self.known.__getitem__
        return [list(chain.from_iterable(map(get, u))) for u in cut]

    def decode(self, ids: list[list[int]]) -> list[str]:
        return self.library.decode(ids) if ids else []


@lru_cache(maxsize=2)
def agenda_encoder(path: str, cached: int = 450_000) -> AgendaEncoder:
    """One encoder for each worker process, so that its cache outlives a task."""
    return AgendaEncoder(path, cached)


def tokenize(docs: DataFrame, model: str, cached: int = 450_000) -> DataFrame:
    """``doc_id, ids, decoded`` for each row; a null text is an empty one and has no ids.

    ``cached``: units that a worker keeps at least; fewer take less memory and more time.
    """
    return _mapped(docs, model, False, cached)


def digests(docs: DataFrame, model: str) -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256`` for each row, from the same encoder.

    Ids and decoded texts are digested where they are made, so only narrow rows leave a worker.
    """
    return _mapped(docs, model, True)


def _mapped(docs: DataFrame, model: str, digest: bool, cached: int = 450_000) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = agenda_encoder(model, cached)
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                ids = encoder.encode([t or "" for t in part.column(1).to_pylist()])
                texts = encoder.decode(ids)
                if not digest:
                    columns = [pa.array(ids, pa.list_(pa.int32())), pa.array(texts, pa.string())]
                    yield pa.RecordBatch.from_arrays([part.column(0), *columns], ["doc_id", "ids", "decoded"])
                    continue
                sha = [hashlib.sha256(str(x)[1:-1].replace(" ", "").encode()).hexdigest() for x in ids]
                back = [hashlib.sha256(t.encode("utf-8")).hexdigest() for t in texts]
                columns = [pa.array([len(x) for x in ids], pa.int64()), pa.array(sha), pa.array(back)]
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), *columns], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
                )

    schema = (
        "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
        if digest
        else "doc_id long, ids array<int>, decoded string"
    )
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(tidy(run), schema)
