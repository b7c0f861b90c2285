"""Near-duplicate documents by circulant MinHash, banding and exact Jaccard verification.

Two permutations make a whole signature: the first scatters shingle hashes over a universe of
2^32 cells, the second is evaluated at circular shifts of the cell number, one shift for each
coordinate, and the minimum is kept. Bands of coordinates propose pairs; every link rests on the
exact ``100 * |A & B| >= threshold * |A | B|`` over full shingle sets.

How pairs are kept few without losing a link:

1. documents with equal shingle sets form a class at once (a hash aggregation), only its smallest
   doc_id goes on;
2. in each bucket every class is compared with the bucket's smallest class only (a star, linear
   in the bucket), and components are taken over the verified links;
3. buckets whose classes beside the smallest one, the pivot, all fell into one component are settled. In the others every
   class has been compared with the pivot, and is described by its difference to the pivot. Two classes of
   different components can link only if their differences overlap by a number that their sizes give, so
   they meet by the rarest elements of the differences; what a whole group of near copies shares is in no
   difference, and what sets them all apart from the pivot is frequent and comes last. Elements that only one component
   has are no meeting places, and two classes that met at an element just before do not meet again.
4. Meeting places with many pairs of different components are first worked off as stars, which merges components in
   rounds of linear size; only pairs that are left are compared one by one.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from groupflow.llm.shingles import shingle_set
from groupflow.llm.worker_memory import tidy
from groupflow.operators.graph import components
from groupflow.storage import listed, materialize, release


@dataclass(frozen=True)
class MinHashParams:
    """``bands * rows`` coordinates. With 32 bands of 6 rows a pair at similarity 0.85 is missed
    with probability 3e-7, one at 0.8 with 6e-5. ``linear``: pairs for each row of a meeting place up to which all of
    them are compared at once; above, components are merged by stars first. It changes the work, not the result."""

    threshold: int = 85
    width: int = 5
    bands: int = 32
    rows: int = 6
    linear: float = 8.0


def _second_permutation(cells: np.ndarray) -> np.ndarray:
    """A bijection of 32-bit cells, in place."""
    cells ^= cells >> np.uint32(16)
    cells *= np.uint32(0x7FEB352D)
    cells ^= cells >> np.uint32(15)
    cells *= np.uint32(0x846CA68B)
    cells ^= cells >> np.uint32(16)
    return cells


def signature(hashes: np.ndarray, size: int) -> np.ndarray:
    """Circulant MinHash signature of a non-empty set of 64-bit hashes."""
    first = ((hashes * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(32)).astype(np.uint32)
    shifts = np.arange(1, size + 1, dtype=np.uint32)
    low = np.full(size, 0xFFFFFFFF, np.uint32)
    for at in range(0, len(first), 512):
        block = first[at : at + 512, None] + shifts[None, :]  # circular: modulo 2^32
        np.minimum(low, _second_permutation(block).min(axis=0), out=low)
    return low


_SIGNED = pa.schema(
    [
        ("doc_id", pa.int64()),
        ("n_shingles", pa.int64()),
        ("set_key", pa.binary()),
        ("bands", pa.list_(pa.int64())),
    ]
)


def _signer(p: MinHashParams):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mult = (np.arange(1, p.rows + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)
        for batch in batches:
            ids, sizes, keys, bands = batch.column(0), [], [], []
            for text in batch.column(1):
                hashes = shingle_set(text.as_py(), p.width)
                sizes.append(len(hashes))
                if not len(hashes):
                    keys.append(None)
                    bands.append([])
                    continue
                keys.append(hashlib.md5(hashes.tobytes()).digest())
                sig = signature(hashes, p.bands * p.rows).astype(np.uint64).reshape(p.bands, p.rows)
                mixed = (sig * mult).sum(axis=1, dtype=np.uint64)
                mixed ^= mixed >> np.uint64(31)
                bands.append((mixed * np.uint64(0xBF58476D1CE4E5B9)).view(np.int64))
            yield pa.RecordBatch.from_arrays(
                [ids, pa.array(sizes, pa.int64()), pa.array(keys, pa.binary()), pa.array(bands, pa.list_(pa.int64()))],
                schema=_SIGNED,
            )

    return run


def signatures(docs: DataFrame, p: MinHashParams = MinHashParams()) -> DataFrame:
    """``doc_id, n_shingles, set_key, bands``: one narrow row per document, one pass over the texts."""
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(
        tidy(_signer(p)), "doc_id long, n_shingles long, set_key binary, bands array<long>"
    )


def _set_maker(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [shingle_set(t.as_py(), width).view(np.int64) for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sets, pa.list_(pa.int64()))], ["node", "shingles"])

    return run


def _checker(threshold: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for i in range(batch.num_rows):
                a = batch.column(2)[i].values.to_numpy().view(np.uint64)
                b = batch.column(3)[i].values.to_numpy().view(np.uint64)
                shared = len(np.intersect1d(a, b, assume_unique=True))
                keep.append(100 * shared >= threshold * (len(a) + len(b) - shared))
            yield batch.select([0, 1]).filter(pa.array(keep, pa.bool_()))

    return run


def _verified(pairs: DataFrame, sets: DataFrame, p: MinHashParams) -> DataFrame:
    """Pairs ``(src, dst)`` whose full sets reach the threshold. Sizes are compared before sets are joined."""
    size = sets.select("node", "n_shingles")
    near = (
        pairs.join(size.select(F.col("node").alias("src"), F.col("n_shingles").alias("na")), "src")
        .join(size.select(F.col("node").alias("dst"), F.col("n_shingles").alias("nb")), "dst")
        .filter(100 * F.least("na", "nb") >= p.threshold * F.greatest("na", "nb"))
        .select("src", "dst")
    )
    return (
        near.join(sets.select(F.col("node").alias("src"), F.col("shingles").alias("a")), "src")
        .join(sets.select(F.col("node").alias("dst"), F.col("shingles").alias("b")), "dst")
        .select("src", "dst", "a", "b")
        .mapInArrow(tidy(_checker(p.threshold)), "src long, dst long")
    )


def _differences(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """``hub, node, comp, n, d``: for each of ``pairs(src, dst, comp)`` the elements in which the node's set and the pivot's differ.
    ``hub`` names the pivot and its set, should its doc_id stand on several texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hubs, sizes, out = [], [], []
            pivots = batch.column(0).to_pylist()
            for i in range(batch.num_rows):
                a = batch.column(3)[i].values.to_numpy()
                b = batch.column(4)[i].values.to_numpy()
                hubs.append(xxhash.xxh64_intdigest(a.tobytes(), pivots[i] & 0xFFFFFFFFFFFFFFFF) >> 1)
                sizes.append(len(b))
                out.append(np.setxor1d(a, b, assume_unique=True))
            yield pa.RecordBatch.from_arrays(
                [pa.array(hubs, pa.int64()), batch.column(1), batch.column(2), pa.array(sizes, pa.int64()), pa.array(out, pa.list_(pa.int64()))],
                ["hub", "node", "comp", "n", "d"],
            )

    both = pairs.join(sets.select(F.col("node").alias("src"), F.col("shingles").alias("a")), "src")
    both = both.join(sets.select(F.col("node").alias("dst"), F.col("shingles").alias("b")), "dst").select("src", "dst", "comp", "a", "b")
    return both.mapInArrow(tidy(run), "hub long, node long, comp long, n long, d array<long>")


_STEP = 1.25
_PLACE = ["hub", "s", "low", "high"]
_BEFORE = 4  # elements before its own that a row names


def _meetings(gaps: DataFrame, p: MinHashParams) -> DataFrame:
    """``hub, s, low, high, node, n, size, at, own, before``: where classes meet that may link, without loss.

    Sets at the threshold differ in at most ``h = (100 - t) / (100 + t) * (na + nb)`` elements, so their differences ``A`` and
    ``B`` to the pivot overlap in at least ``o = (|A| + |B| - h) / 2``, and in one at least where one of the two does not
    link with the pivot. Both then have an element in common among their first ``size - o + 1``, in any order; the
    rarest come first here. As ``o`` depends on the partner, a class has a prefix for each step of partner sizes.
    ``before``: the meeting places just before in the same order. Where two classes share one of them they met there, as a prefix that
    reaches an element reaches all before it.
    """
    t = p.threshold
    gaps = gaps.withColumn("who", F.xxhash64("hub", "node", "d"))
    step = lambda c: F.floor(F.log(c + 0.5) / math.log(_STEP)).cast("int")
    own = step(F.size("d"))
    each = gaps.select("hub", "who", "comp", own.alias("own"), F.explode("d").alias("s"))
    # elements of one component only meet nothing, but keep their places: all before the first that is met count as before it
    here = F.bit_or(F.expr("shiftleft(1L, own)")).alias("steps")  # steps of sizes there are at the element, by bits
    common = each.groupBy("hub", "s").agg(F.count("*").alias("df"), F.min("comp").alias("lo"), F.max("comp").alias("hi"), here).filter("lo < hi")
    some = each.select("hub", "who", "s").join(common.select("hub", "s", "df", "steps"), ["hub", "s"])
    ranked = some.groupBy("who").agg(F.sort_array(F.collect_list(F.struct("df", "s", "steps"))).alias("r"))
    known = gaps.select("who", "hub", "node", "n", F.size("d").cast("long").alias("size")).dropDuplicates(["who"])
    ranked = ranked.select("who", F.col("r.s").alias("r"), F.col("r.steps").alias("steps")).join(known, "who")
    met = lambda s, i: F.struct(s.alias("s"), F.get("steps", i).alias("steps"), F.slice("r", F.greatest(i + 1 - _BEFORE, F.lit(1)), F.least(i, F.lit(_BEFORE))).alias("before"))
    ranked = ranked.select("hub", "node", "n", "size", F.posexplode(F.transform("r", met)).alias("at", "e"), F.size("r").alias("held"))
    ranked = ranked.select("*", "e.s", "e.steps", "e.before").drop("e")
    ranked = ranked.withColumn("at", F.col("at") + F.col("size") - F.col("held")).drop("held")
    h = F.floor(F.col("n") * (100 - t) / t)
    ranked = ranked.withColumns({"own": step(F.col("size")), "h": h})
    partner = F.sequence(step(F.greatest(F.col("size") - F.col("h"), F.lit(1))), step(F.col("size") + F.col("h")))
    rows = ranked.withColumn("k", F.explode(partner)).filter(F.expr("steps & shiftleft(1L, k) <> 0"))
    # the smallest size in a step, less one for rounding
    least = F.greatest(F.ceil(F.pow(F.lit(_STEP), F.col("k")) - 0.5) - 1, F.lit(1))
    overlap = F.greatest(F.ceil((F.col("size") + least - F.col("h")) / 2), F.lit(1))
    rows = rows.filter(F.col("at") < F.col("size") - overlap + 1)
    return rows.select("hub", "s", F.least("own", "k").alias("low"), F.greatest("own", "k").alias("high"), "node", "n", "size", "at", "own", "before")


def _open(met: DataFrame, comp: DataFrame, name: str) -> tuple[DataFrame, int, int]:
    """Meeting places of several components with the component of each class, their rows and an upper bound of their pairs."""
    rows = met.drop("comp").join(comp, "node", "left").withColumn("comp", F.coalesce("comp", "node"))
    each = rows.groupBy(*_PLACE, "comp").agg(F.count("*").alias("c"))
    place = each.groupBy(*_PLACE).agg(F.count("*").alias("k"), F.sum("c").alias("c"), F.sum(F.col("c") * F.col("c")).alias("q"))
    place = place.filter("k > 1").withColumn("pairs", (F.col("c") * F.col("c") - F.col("q")) / 2)
    rows = materialize(rows.join(place.select(*_PLACE, "c", "pairs"), _PLACE), name)
    n = rows.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.col("pairs") / F.col("c")), F.lit(0.0)).alias("pairs")).first()
    return rows.drop("c", "pairs"), n["n"], n["pairs"]


def _merged(comp: DataFrame, links: DataFrame) -> DataFrame:
    """``node, comp`` after ``links`` between classes; only components are gone through again, not classes."""
    label = lambda c: links.join(comp.withColumnsRenamed({"node": c, "comp": f"{c}_comp"}), c, "left")
    links = label("src").join(comp.withColumnsRenamed({"node": "dst", "comp": "dst_comp"}), "dst", "left")
    links = links.select(F.coalesce("src_comp", "src").alias("src"), F.coalesce("dst_comp", "dst").alias("dst"))
    again = materialize(components(links), "merged").withColumnsRenamed({"node": "comp", "component": "new"})
    known = comp.join(again, "comp", "left").select("node", F.coalesce("new", "comp").alias("comp"))
    # classes that were in no component stand for themselves
    alone = again.join(comp.select(F.col("node").alias("comp")), "comp", "left_anti").select(F.col("comp").alias("node"), F.col("new").alias("comp"))
    return materialize(known.unionByName(alone), "comp")


def _first_meetings(met: DataFrame, p: MinHashParams) -> DataFrame:
    """``src, dst``: classes of different components that may link, where they meet first, or at least not just before."""
    side = lambda node, x: met.select(*_PLACE, F.col("node").alias(node), *[F.col(c).alias(f"{c}_{x}") for c in ("comp", "n", "size", "at", "own", "before")])
    t = p.threshold
    need = F.ceil((F.col("size_a") + F.col("size_b") - F.floor((F.col("n_a") + F.col("n_b")) * (100 - t) / (100 + t))) / 2)
    can = (
        (F.col("src") < F.col("dst"))
        & (F.col("comp_a") != F.col("comp_b"))
        & ((F.col("low") == F.col("high")) | (F.col("own_a") != F.col("own_b")))
        & (100 * F.least("n_a", "n_b") >= t * F.greatest("n_a", "n_b"))
        & (F.least(F.col("size_a") - F.col("at_a"), F.col("size_b") - F.col("at_b")) >= need)
        & ~F.arrays_overlap("before_a", "before_b")
    )
    return side("src", "a").join(side("dst", "b"), _PLACE).filter(can).select("src", "dst")


def _settle(pairs: DataFrame, sets: DataFrame, comp: DataFrame, p: MinHashParams) -> DataFrame:
    """``node, comp`` once all classes of ``pairs(src, dst, comp)``, pivot and class, are compared as far as they can still merge."""
    if pairs.isEmpty():
        return comp
    gaps = materialize(_differences(pairs, sets), "gaps")
    met, n, cross = _open(materialize(_meetings(gaps, p), "meetings"), comp, "open")
    while n:
        last = cross <= p.linear * n
        if last:
            star = _first_meetings(met, p).distinct()
        else:
            centre = met.groupBy(*_PLACE).agg(F.min(F.struct("node", "comp")).alias("m"))
            star = met.join(centre, _PLACE).filter("m.comp <> comp").select(F.col("m.node").alias("src"), F.col("node").alias("dst")).distinct()
        star = materialize(star, "pairs")
        links = materialize(_verified(star, sets, p).distinct(), "links")
        found = links.count()
        if found:
            comp = _merged(comp, links)
        if last:
            break
        if found * 100 < star.count():
            # stars find little more: all pairs that are left
            p = replace(p, linear=math.inf)
        met, n, cross = _open(met, comp, "open")
    return comp


def near_duplicates(docs: DataFrame, p: MinHashParams = MinHashParams()) -> DataFrame:
    """``doc_id, n_shingles, component_id, kept``: one row per row of ``docs``.

    Null or empty texts, and texts of white space, have no shingles and link with nothing. Rows
    that repeat a doc_id are one node (with the sets of all its rows). A null doc_id gets a null
    component and is kept. An empty table gives an empty result; other columns are not read.
    """
    signed = materialize(signatures(docs, p), "signed")
    # 1. classes of equal sets; salted first so that a huge class aggregates on the map side only
    classes = materialize(
        signed.filter("set_key is not null and doc_id is not null")
        .groupBy("set_key")
        .agg(F.min("doc_id").alias("node"), F.first("bands").alias("bands"), F.max("n_shingles").alias("n_shingles")),
        "classes",
    )
    buckets = classes.select("node", F.posexplode("bands").alias("band", "bucket"))
    # 2. stars
    low = buckets.groupBy("band", "bucket").agg(F.min("node").alias("low"), F.count("*").alias("n")).filter("n > 1")
    crowded = materialize(buckets.join(low, ["band", "bucket"]).select("band", "bucket", "node", "low"), "crowded")
    stars = crowded.filter("node <> low").select(F.col("low").alias("src"), F.col("node").alias("dst")).distinct()
    wanted = materialize(crowded.select("node").distinct(), "wanted")
    texts = (
        docs.select(F.col("doc_id").cast("long").alias("node"), "text")
        .join(listed(wanted), "node", "left_semi")
        .mapInArrow(tidy(_set_maker(p.width)), "node long, shingles array<long>")
    )
    sets = materialize(texts.withColumn("n_shingles", F.size("shingles").cast("long")), "sets")
    # rows that repeat a doc_id with other texts: one set each, all of them are compared
    links = materialize(_verified(stars, sets, p), "links")
    comp = materialize(components(links), "comp").withColumnRenamed("component", "comp")
    # 3. and 4. what the stars left open
    labelled = crowded.join(comp, "node", "left").withColumn("comp", F.coalesce("comp", "node"))
    labelled = labelled.filter("node <> low")
    open_buckets = labelled.groupBy("band", "bucket").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).filter("lo < hi")
    rest = labelled.join(open_buckets.select("band", "bucket"), ["band", "bucket"])
    rest = materialize(rest.select(F.col("low").alias("src"), F.col("node").alias("dst"), "comp").distinct(), "rest")
    final = _settle(rest, sets, comp, p).select("node", F.col("comp").alias("component"))
    by_class = classes.join(final, "node", "left").select(
        "set_key", F.coalesce("component", "node").alias("component_id")
    )
    out = (
        signed.join(by_class, "set_key", "left")
        .withColumn("component_id", F.coalesce("component_id", "doc_id"))
        .select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))
    )
    release(sets, crowded)
    return out


def drop_near_duplicates(docs: DataFrame, p: MinHashParams = MinHashParams()) -> DataFrame:
    """Documents of ``docs`` that are the smallest doc_id of their near-duplicate group.

    Of rows that repeat a doc_id one stays, the first by its text. Rows with a null doc_id, and those with null, empty
    or white texts, link with nothing and are kept. Ties do not occur: a group has one smallest doc_id. Other
    columns are carried along, whatever their names. An empty table gives an empty result.
    """
    found = materialize(near_duplicates(docs, p).select("doc_id", "kept"), "found")
    gone = materialize(found.filter("not kept").select("doc_id").distinct(), "gone")
    kept = docs.join(listed(gone), "doc_id", "left_anti")
    again = materialize(found.filter("kept and doc_id is not null").groupBy("doc_id").count().filter("count > 1").select("doc_id"), "again")
    if not again.isEmpty():
        order = Window.partitionBy("doc_id").orderBy(F.xxhash64("text"), "text")
        one = kept.join(again, "doc_id", "left_semi").select("*", F.row_number().over(order).alias("_place")).filter("_place = 1").drop("_place")
        kept = kept.join(again, "doc_id", "left_anti").unionByName(one)
    return kept.select(docs.columns)
