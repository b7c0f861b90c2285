"""Language identification by compression.

Each language owns a zstandard raw-content dictionary made of sample texts. A text is encoded,
chunk by chunk, once with every dictionary, and the language whose dictionary makes it smallest
wins. The relative gap to the runner-up is the margin; a narrow one marks the prediction rejected.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class LanguageParams:
    """``docs_per_language`` texts at most are sampled (the smallest hashes of doc_id) and cut to
    pieces that fill ``dictionary_bytes`` for each language; with ``max_languages`` that bounds what reaches the driver.
    ``chunk_bytes``: a text is encoded in pieces of this size, so that a long text does not become
    its own dictionary. ``min_margin``: a smaller relative gap is a rejection."""

    docs_per_language: int = 600
    dictionary_bytes: int = 96 * 1024
    chunk_bytes: int = 1024
    level: int = 6
    min_margin: float = 0.01
    max_languages: int = 200


def _filled(pieces: list[str], size: int) -> bytes:
    """A dictionary of ``size`` bytes at most: each piece has an equal share of what shorter ones leave, cut between characters."""
    left, cut = size, {}
    order = sorted(range(len(pieces)), key=lambda i: (len(pieces[i].encode("utf-8", "replace")), pieces[i]))
    for n, i in enumerate(order):
        share = max(left // (len(order) - n) - 1, 0)
        cut[i] = pieces[i].encode("utf-8", "replace")[:share].decode("utf-8", "ignore").encode()
        left -= len(cut[i]) + 1
    return b"\n".join(cut[i] for i in range(len(pieces)) if cut[i])


def train(labelled: DataFrame, p: LanguageParams = LanguageParams()) -> dict[str, bytes]:
    """Dictionary contents by language from ``labelled(doc_id, text, lang)``.

    Rows with a null text, doc_id or lang are skipped; of rows that repeat a doc_id one counts. The sample is chosen on
    ids alone, from the rows whose hash is small, so that no language gathers in a task; only the chosen
    rows' texts are fetched. More than ``max_languages`` languages raise an error. Without rows there is no dictionary.
    """
    known = labelled.filter("lang is not null and text is not null and doc_id is not null")
    count = known.groupBy("lang").agg(F.count("*").alias("n"))
    if count.count() > p.max_languages:
        raise ValueError(f"more than {p.max_languages} languages")
    share = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) / (1 << 30)
    # so few rows that the window holds about twice the sample
    few = known.select("doc_id", "lang").join(F.broadcast(count), "lang").filter(share < 2.0 * p.docs_per_language / F.col("n"))
    rank = F.row_number().over(Window.partitionBy("lang").orderBy(F.xxhash64("doc_id"), "doc_id"))
    chosen = few.select("doc_id", "lang").distinct().withColumn("rank", rank).filter(F.col("rank") <= p.docs_per_language)
    # room for the shares that short texts leave
    size = 4 * p.dictionary_bytes // p.docs_per_language
    # the piece of each sampled text is a bounded sample of it: chosen by the document's hash, not its beginning
    start = F.pmod(F.xxhash64("doc_id", F.lit(7)), F.greatest(F.length("text") - size, F.lit(1))) + 1
    pieces = (
        known.join(F.broadcast(chosen.select("doc_id", "lang")), ["doc_id", "lang"], "left_semi")
        .groupBy("lang", "doc_id")
        .agg(F.min(F.substring(F.col("text"), start.cast("int"), F.lit(size))).alias("piece"))
        .collect()
    )
    by_language: dict[str, list[str]] = {}
    # in the order of a hash, so that a dictionary's end, which is cheapest to refer to, is no special part of the corpus
    for row in sorted(pieces, key=lambda r: (r["lang"], zlib.crc32(str(r["doc_id"]).encode()), r["doc_id"])):
        by_language.setdefault(row["lang"], []).append(row["piece"])
    return {lang: _filled(x, p.dictionary_bytes) for lang, x in by_language.items()}


def _sizes(data: bytes, encoders: list, chunk: int) -> list[int]:
    pieces = [data[i : i + chunk] for i in range(0, len(data), chunk)]
    if len(pieces) > 1 and len(pieces[-1]) < chunk // 2:
        tail = pieces.pop()
        pieces[-1] += tail
    return [sum(len(c.compress(x)) for x in pieces) for c in encoders]


def decide(text: str | None, names: list[str], encoders: list, p: LanguageParams) -> tuple[str, float, bool]:
    """Language, score and rejection of one whole text. ``und``, 0 and rejected without a letter."""
    if not text or not names or not any(map(str.isalpha, text)):
        return "und", 0.0, True
    sizes = _sizes(text.encode("utf-8", "replace"), encoders, p.chunk_bytes)
    order = sorted(range(len(sizes)), key=lambda i: (sizes[i], i))
    best = sizes[order[0]]
    margin = 1.0 if len(order) == 1 else (sizes[order[1]] - best) / max(sizes[order[1]], 1)
    return names[order[0]], margin, margin < p.min_margin


def identify(docs: DataFrame, dictionaries: dict[str, bytes], p: LanguageParams = LanguageParams()) -> DataFrame:
    """``doc_id, lang_pred, score, rejected`` for each row. ``score`` is the margin, from 0 to 1.

    Null texts and texts without a letter are ``und``. Ties go to the first language by name.
    Rows are independent, so repeated and empty rows need no care; other columns are not read.
    """
    names = sorted(dictionaries)
    shared = docs.sparkSession.sparkContext.broadcast([dictionaries[n] for n in names])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoders = []
        for content in shared.value:
            dictionary = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            dictionary.precompute_compress(level=p.level)
            encoders.append(
                zstandard.ZstdCompressor(level=p.level, dict_data=dictionary, write_checksum=False, write_content_size=False)
            )
        for batch in batches:
            out = [decide(t.as_py(), names, encoders, p) for t in batch.column(1)]
            langs, scores, rejected = zip(*out) if out else ((), (), ())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array(rejected, pa.bool_())],
                ["doc_id", "lang_pred", "score", "rejected"],
            )

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(
        run, "doc_id long, lang_pred string, score double, rejected boolean"
    )
