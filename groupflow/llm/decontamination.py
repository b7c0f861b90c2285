"""Benchmark decontamination by q-gram filtering and banded alignment.

Every run of ``short + stride - 1`` characters of an item holds one of its overlapping patterns whole. Two strings of length m within k edits share at
least ``m + 1 - q * (k + 1)`` q-grams, and those lie within ``k`` diagonals of one another. The
q-grams of whole items are indexed once. Where a text shares enough of them with an item for one pattern,
they are counted for each pattern in overlapping bands of diagonals; only bands that meet the bound are
aligned, in the band, and a pattern within its edit budget is a leak. Patterns without an edit need no alignment.

The items' index is broadcast in blocks of bounded size, one pass over the texts for each block; the
texts are scanned as code-point arrays and never shuffled.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupflow.llm.worker_memory import tidy
from groupflow.storage import listed, materialize

_OTHER = re.compile(r"[\W_]+")
_A = 0x9E3779B97F4A7C15


@dataclass(frozen=True)
class DecontaminationParams:
    """``q``: length of the q-grams, ``little``: that for items too short for the bound of ``edits`` at
    ``q``. ``least``: shorter items, in normalised characters, stand in texts by chance and are not searched. ``window``, ``short``, ``stride``: patterns of an item, in normalised characters, of two widths: a copied
    passage of ``short + stride - 1`` (99) characters is found wherever it starts in the item, and the wider
    patterns hold more edits. ``edits``: the budget, as a share of the pattern.
    ``block_chars``: characters of items indexed at once, which bounds what is broadcast: 40 bytes for each."""

    q: int = 12
    little: int = 6
    least: int = 12
    window: int = 128
    short: int = 92
    stride: int = 8
    edits: float = 0.05
    block_chars: int = 2_000_000


def normalise(text: str | None) -> str:
    """Lower case; runs of anything but letters and digits become one space; none at the ends."""
    return _OTHER.sub(" ", text.lower()).strip() if text else ""


def _codes(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)


def _grams(codes: np.ndarray, q: int) -> np.ndarray:
    """Hashes of all q-grams, by doubling."""
    if len(codes) < q:
        return np.empty(0, np.uint64)
    total, width, out, factor = len(codes), 1, None, _A
    h = codes.astype(np.uint64)
    h = (h + np.uint64(1)) * np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(29)
    done = 0
    while True:
        if q >> (width.bit_length() - 1) & 1:
            # append the h-block of this width after what is done
            tail = h[done : total - width + 1]
            out = tail.copy() if out is None else out[: total - done - width + 1] * np.uint64(factor) + tail
            done += width
        if done == q:
            break
        h = h[: len(h) - width] * np.uint64(factor) + h[width:]
        factor = factor * factor & 0xFFFFFFFFFFFFFFFF
        width *= 2
    out = out[: total - q + 1]
    return out ^ (out >> np.uint64(31))


@dataclass
class _Patterns:
    """An index of items, one entry for each width of its patterns: sorted distinct q-gram hashes and where each
    one stands. Patterns are numbered entry by entry."""

    item: list[int]
    same: np.ndarray  # one number for the entries of an item
    codes: np.ndarray  # of all entries, one after another
    begin: np.ndarray  # of each entry in codes
    width: np.ndarray  # of each entry's patterns
    budget: np.ndarray
    least: np.ndarray
    first: np.ndarray  # number of each entry's first pattern, and of all patterns
    starts: np.ndarray  # of each pattern in its item
    of: np.ndarray  # the entry of each pattern
    hashes: np.ndarray
    offsets: np.ndarray
    owner: np.ndarray
    place: np.ndarray
    table: np.ndarray


def build(items: list[tuple[int, str | None]], p: DecontaminationParams) -> _Patterns:
    """Patterns of whole items. An item shorter than a q-gram is not searched: it is no evidence of a leak."""
    item, same, codes, width, budget, least, starts, grams = [], [], [], [], [], [], [], []
    for number, (item_id, text) in enumerate(items):
        c = _codes(normalise(text))
        n = len(c)
        if n < p.q:
            continue
        for m in sorted({min(n, p.window), min(n, p.short)}):
            k = int(p.edits * m)
            while k and m + 1 - p.q * (k + 1) < 1:
                k -= 1
            item.append(item_id)
            same.append(number)
            codes.append(c)
            width.append(m)
            budget.append(k)
            least.append(m + 1 - p.q * (k + 1))
            starts.append(np.array([*range(0, n - m, p.stride), n - m]))
            grams.append(_grams(c, p.q))
    lengths = [len(g) for g in grams]
    every = np.concatenate(grams) if grams else np.empty(0, np.uint64)
    owner = np.repeat(np.arange(len(grams)), lengths)
    place = np.concatenate([np.arange(n) for n in lengths]) if grams else np.empty(0, np.int64)
    owner, place = owner.astype(np.int32), place.astype(np.int32)
    order = np.argsort(every, kind="stable")
    hashes, first = np.unique(every[order], return_index=True)
    table = np.zeros(1 << 22, np.bool_)
    table[hashes >> np.uint64(42)] = True
    sizes = [len(c) for c in codes]
    many = [len(x) for x in starts]
    whole = lambda parts: np.concatenate(parts) if parts else np.empty(0, np.int64)
    return _Patterns(
        item, np.array(same, np.int64), whole(codes), np.cumsum([0, *sizes]), np.array(width, np.int64), np.array(budget, np.int64), np.array(least, np.int64),
        np.cumsum([0, *many]), whole(starts), np.repeat(np.arange(len(many)), many),
        hashes, np.append(first, len(every)), owner[order], place[order], table,
    )


def _aligned(text: np.ndarray, pattern: np.ndarray, low: np.ndarray, width: int) -> np.ndarray:
    """Least edits of a pattern against a part of ``text``, for each band ``[low, low + width)`` of diagonals.

    ``pattern`` is one for all bands, or has a row for each band. Rows of the alignment are the pattern's characters; a row holds the band's diagonals for all candidates at
    once. Insertions run along a row, which a running minimum resolves.
    """
    steps = np.arange(width)
    at = low[:, None] + steps[None, :]
    cost = np.zeros(at.shape, np.int32)
    edge = np.full((len(low), 1), 1 << 20, np.int32)
    n = len(text)
    for j, c in enumerate(pattern if pattern.ndim == 1 else pattern.T[:, :, None]):
        where = at + j
        inside = (where >= 0) & (where < n)
        same = inside & (text[np.clip(where, 0, max(n - 1, 0))] == c)
        over = cost + np.where(same, 0, 1).astype(np.int32)
        skipped = np.concatenate([cost[:, 1:] + 1, edge], axis=1)  # a pattern character without a partner
        best = np.minimum(over, skipped)
        cost = np.minimum.accumulate(best - steps, axis=1) + steps
    return cost.min(axis=1)


def _counted(a: np.ndarray, b: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct pairs with ``-n <= b < n``, as ``a * 2n + b + n``, and how often each one stands."""
    return np.unique(a * (2 * n) + b + n, return_counts=True)


def _leaks(texts: list[str | None], index: _Patterns, p: DecontaminationParams) -> dict[int, dict[int, tuple[int, int]]]:
    """For each number of a text with leaks: item -> (least edits, start in the normalised text)."""
    parts = [_codes(normalise(t)) for t in texts]
    gap = np.zeros(p.q, np.uint32)
    joined = np.concatenate([x for c in parts for x in (c, gap)]) if parts else gap
    ends = np.cumsum([len(c) + p.q for c in parts])
    begins = ends - [len(c) + p.q for c in parts]
    grams = _grams(joined, p.q)
    at = np.flatnonzero(index.table[grams >> np.uint64(42)])
    near = np.searchsorted(index.hashes, grams[at])
    near[near == len(index.hashes)] = 0
    exact = index.hashes[near] == grams[at]
    at, near = at[exact], near[exact]
    if not len(at):
        return {}
    counts = index.offsets[near + 1] - index.offsets[near]
    rank = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
    posting = np.repeat(index.offsets[near], counts) + rank
    at = np.repeat(at, counts)
    owner, place = index.owner[posting].astype(np.int64), index.place[posting].astype(np.int64)
    doc = np.searchsorted(ends, at, side="right")
    # no pattern of a pair of text and item can meet the bound when all the pair's q-grams together do not
    pair = doc * len(index.item) + owner
    _, inverse, total = np.unique(pair, return_inverse=True, return_counts=True)
    keep = total[inverse] >= index.least[owner]
    owner, place, at, doc = owner[keep], place[keep], at[keep], doc[keep]
    if not len(owner):
        return {}
    # from items to their patterns: those that hold the q-gram whole, starts on a grid and one at the item's end
    low, last = index.first[owner], index.first[owner + 1] - 1
    since = np.maximum(place - (index.width[owner] - p.q), 0)
    begin = np.minimum(low - (-since // p.stride), last)
    end = np.minimum(low + place // p.stride + 1, last)
    end += index.starts[last] <= place
    counts = np.maximum(end - begin, 0)
    rank = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
    pattern = np.repeat(begin, counts) + rank
    at, doc = np.repeat(at, counts), np.repeat(doc, counts)
    diagonal = at - np.repeat(place, counts) + index.starts[pattern]
    found: dict[int, dict[int, tuple[int, int]]] = {}

    def note(docs: np.ndarray, items: np.ndarray, edits: np.ndarray, starts: np.ndarray) -> None:
        for d, i, e, x in zip(docs.tolist(), items.tolist(), edits.tolist(), starts.tolist()):
            new = (e, max(x - int(begins[d]), 0))
            old = found.setdefault(d, {}).get(index.item[i])
            found[d][index.item[i]] = new if old is None else min(old, new)

    # all q-grams of a pattern on one diagonal: a copy without edits, and the pair is settled
    reach = len(joined) + max(p.window, p.short)  # above every diagonal and band, of either sign
    key, count = _counted(pattern, diagonal, reach)
    one, here = key // (2 * reach), key % (2 * reach) - reach
    item = index.of[one]
    full = count == index.width[item] - p.q + 1
    one, here, item = one[full], here[full], item[full]
    where = np.searchsorted(ends, here, side="right")
    note(where, item, np.zeros(len(one), np.int64), here)
    settled = np.unique(where * len(index.item) + index.same[item])
    keep = ~np.isin(doc * len(index.item) + index.same[index.of[pattern]], settled)
    pattern, diagonal, doc = pattern[keep], diagonal[keep], doc[keep]
    span = 2 * index.budget[index.of[pattern]] + 1
    band = np.concatenate([diagonal // span, diagonal // span - 1])  # each band is two spans wide
    pattern, doc = np.tile(pattern, 2), np.tile(doc, 2)
    key, count = _counted(doc * len(index.of) + pattern, band, reach)
    one = key // (2 * reach)
    key = np.stack([one // len(index.of), one % len(index.of), key % (2 * reach) - reach])
    key = key[:, count >= index.least[index.of[key[1]]]]
    item = index.of[key[1]]
    for m in np.unique(index.width[item]):
        rows = np.flatnonzero(index.width[item] == m)
        k = int(index.budget[item[rows[0]]])
        span = 2 * k + 1
        for some in np.array_split(rows, -(-len(rows) // 4096)):
            docs, patterns, bands = key[:, some]
            begin = index.begin[item[some]] + index.starts[patterns]
            edits = _aligned(joined, index.codes[begin[:, None] + np.arange(m)], bands * span, 2 * span)
            near = edits <= k
            note(docs[near], item[some][near], edits[near], bands[near] * span)
    return found


def _searched(n: int, p: DecontaminationParams) -> bool:
    """Whether an item of ``n`` characters keeps its edit budget with q-grams of length ``q``."""
    k = int(p.edits * min(n, p.short))
    return n >= p.q and n + 1 - p.q * (k + 1) >= 1


def unsearchable(benchmark: DataFrame, p: DecontaminationParams = DecontaminationParams()) -> list[int]:
    """Ids of items that are no evidence of a leak: null ones and those of less than ``least`` normalised characters."""
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), "text").filter("item_id is not null")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            few = pa.array([len(normalise(t.as_py())) < p.least for t in batch.column(1)], pa.bool_())
            yield batch.select([0]).filter(few)

    return sorted(r["item_id"] for r in items.mapInArrow(run, "item_id long").collect())


def _blocks(benchmark: DataFrame, p: DecontaminationParams) -> Iterator[tuple[_Patterns, DecontaminationParams]]:
    """Indexes over parts of the benchmark, each of bounded size; those of short items apart, with shorter q-grams."""
    items = benchmark.select(F.col("item_id").cast("long"), "text").filter("item_id is not null and text is not null")
    total = items.agg(F.sum(F.length("text")).alias("n")).first()["n"] or 0
    n = max(1, -(-total // p.block_chars))
    for k in range(n):
        rows = items.filter(F.pmod(F.xxhash64("item_id"), F.lit(n)) == k).collect()
        whole: list[tuple[int, str]] = []
        short: list[tuple[int, str]] = []
        for r in sorted(rows, key=lambda r: (r["item_id"], r["text"])):
            size = len(normalise(r["text"]))
            if size >= p.least:
                (whole if _searched(size, p) else short).append((r["item_id"], r["text"]))
        for some, one in ((whole, p), (short, replace(p, q=p.little))):
            index = build(some, one)
            if index.item:
                yield index, one


def find_leaks(docs: DataFrame, benchmark: DataFrame, p: DecontaminationParams = DecontaminationParams()) -> DataFrame:
    """``doc_id, item_id, edits, start``: one row for each row of ``docs`` and item with a leaked pattern, so for
    any copied passage of ``short + stride - 1`` normalised characters or an item shorter than a pattern.

    ``edits`` is the least over the item's patterns, ``start`` about where it stands in the normalised
    text. Null and empty texts have no leak; null and too short items (less than ``least`` normalised
    characters, see :func:`unsearchable`) leak nowhere. Equal items leak each for itself. Repeated documents give repeated rows. Other columns are not read.
    """
    rows = docs.select(F.col("doc_id").cast("long"), "text")
    schema = "doc_id long, item_id long, edits int, start long"
    out = None
    for index, one in _blocks(benchmark, p):
        shared = docs.sparkSession.sparkContext.broadcast(index)

        def run(batches: Iterator[pa.RecordBatch], shared=shared, p=one) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                at = 0
                texts = batch.column(1).to_pylist()
                while at < len(texts):
                    # slices of bounded length, a very long text alone
                    to, size = at, 0
                    while to < len(texts) and (to == at or size + len(texts[to] or "") <= 400_000):
                        size += len(texts[to] or "")
                        to += 1
                    found = _leaks(texts[at:to], shared.value, p)
                    ids = batch.column(0).slice(at, to - at).to_pylist()
                    rows = [(ids[d], i, e, s) for d, x in sorted(found.items()) for i, (e, s) in sorted(x.items())]
                    at = to
                    if rows:
                        yield pa.RecordBatch.from_arrays(
                            [pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int64(), pa.int32(), pa.int64()))],
                            ["doc_id", "item_id", "edits", "start"],
                        )

        part = rows.mapInArrow(tidy(run), schema)
        out = part if out is None else out.unionByName(part)
    return out if out is not None else docs.sparkSession.createDataFrame([], schema)


def drop_leaks(docs: DataFrame, benchmark: DataFrame, p: DecontaminationParams = DecontaminationParams()) -> DataFrame:
    """``docs`` without the rows of documents in which an item leaked; rows with a null doc_id are kept."""
    gone = materialize(find_leaks(docs, benchmark, p).select("doc_id").distinct(), "leaked")
    return docs.join(listed(gone), "doc_id", "left_anti").select(docs.columns)
