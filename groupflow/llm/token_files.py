"""Token-id files: concatenated ids with Elias-Fano document boundaries.

A file is ``payload, footer, footer length, magic``. The payload holds the ids of all its documents
one after another, two bytes each where the vocabulary allows it, else four. The footer holds two
Elias-Fano structures, ascending document ids and document ends, so a file is written in one
streaming pass and a document is found by two selects, without a table of 64-bit offsets.
"""

from __future__ import annotations

import os
import re
import struct
import sys
import uuid
import zlib
from array import array
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from groupflow.llm.elias_fano import EliasFano
from groupflow.llm.piece_cache import LazyCache
from groupflow.storage import materialize, scratch_path

_MAGIC = b"GFTOK01\n"
_FOOT = "<BQQqQ"
# fixed values: characters whose classes are the same in all tables, and the byte-level words of such texts
_LETTERS = "A-Za-zÀ-ÖØ-öø-ſ"
_COMMON = re.compile(f"[\t\n\r -~¡¿«»{_LETTERS}]*")
_WORDS = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d| ?[{_LETTERS}]+| ?[0-9]+| ?[^\\s0-9{_LETTERS}]+|\\s+(?!\\S)|\\s+")
# the printable stand-ins for bytes: printable ones stand for themselves, others follow from 256 on
_PRINTABLE = {*range(33, 127), *range(161, 173), *range(174, 256)}
_SHOWN = {b: (b if b in _PRINTABLE else 256 + sum(c not in _PRINTABLE for c in range(b))) for b in range(256)}


class PieceEncoder:
    """Ids of texts from the tokenizers library, with a bounded cache of encoded words.

    A byte-level pre-tokenizer cuts a text into words that the model encodes one by one. Texts of
    common characters are cut here by the same rule, and only new words are given to the library's
    model; other texts, texts that hold an added token, and any text under another pre-tokenizer, are encoded whole.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.width = 2 if self.tokenizer.get_vocab_size() <= 65536 else 4
        self.dtype = np.dtype(f"<u{self.width}")
        self.code = "H" if self.width == 2 else "I"
        kind = str(self.tokenizer.pre_tokenizer)
        self.cuts = (
            self.tokenizer.normalizer is None and kind.startswith("ByteLevel(add_prefix_space=False") and "use_regex=True" in kind
        )
        added = [t.content for t in self.tokenizer.get_added_tokens_decoder().values() if t.content]
        self.added = re.compile("|".join(map(re.escape, added)) or "(?!)")
        self.words = LazyCache(400_000, self._word)

    def _bytes(self, ids: list[int]) -> bytes:
        coded = array(self.code, ids)
        if sys.byteorder == "big":
            coded.byteswap()
        return coded.tobytes()

    def _word(self, word: str) -> bytes:
        shown = word.encode().decode("latin-1").translate(_SHOWN)
        return self._bytes([t.id for t in self.tokenizer.model.tokenize(shown)])

    def encode_whole(self, texts: list[str]) -> list[bytes]:
        """By the library alone."""
        return [self._bytes(x.ids) for x in self.tokenizer.encode_batch(texts, add_special_tokens=False)]

    def encode(self, texts: list[str]) -> list[bytes]:
        """Little-endian ids of each text."""
        if not self.cuts:
            return self.encode_whole(texts)
        cut = {i: _WORDS.findall(t) for i, t in enumerate(texts) if t and _COMMON.fullmatch(t) and not self.added.search(t)}
        whole = [i for i, t in enumerate(texts) if t and i not in cut]
        out, get = [b""] * len(texts), self.words.__getitem__
        for i, found in cut.items():
            out[i] = b"".join(map(get, found))
        for i, ids in zip(whole, self.encode_whole([texts[i] for i in whole])):
            out[i] = ids
        return out


@lru_cache(maxsize=2)
def piece_encoder(path: str) -> PieceEncoder:
    """One encoder for each worker process, so that its cache outlives a task."""
    return PieceEncoder(path)


class TokenFile:
    """Random access to one file."""

    def __init__(self, path: str):
        where, name = fs.FileSystem.from_uri(path)
        self.file = where.open_input_file(name)
        size = self.file.size()
        tail = self.file.read_at(8 + len(_MAGIC), size - 8 - len(_MAGIC))
        if tail[8:] != _MAGIC:
            raise ValueError(f"not a token file: {path}")
        (length,) = struct.unpack("<Q", tail[:8])
        foot = self.file.read_at(length, size - 8 - len(_MAGIC) - length)
        self.width, self.n_docs, self.n_null, self.first_id, self.n_ids = struct.unpack_from(_FOOT, foot)
        self.doc_ids, at = EliasFano.from_bytes(foot, struct.calcsize(_FOOT))
        self.ends, _ = EliasFano.from_bytes(foot, at)

    def doc_id(self, i: int) -> int | None:
        return None if i < self.n_null else self.doc_ids.select(i - self.n_null) + self.first_id

    def bounds(self, i: int) -> tuple[int, int]:
        return (self.ends.select(i - 1) if i else 0), self.ends.select(i)

    def ids(self, i: int) -> np.ndarray:
        lo, hi = self.bounds(i)
        return np.frombuffer(self.file.read_at((hi - lo) * self.width, lo * self.width), f"<u{self.width}")

    def close(self) -> None:
        self.file.close()


def _writer(tokenizer: str, folder: str, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, out = piece_encoder(tokenizer), None
        tail = np.array([end_id], encoder.dtype).tobytes()
        doc_ids: list[np.ndarray] = []
        lengths: list[np.ndarray] = []
        n_null = 0
        path = f"{folder}/{uuid.uuid4().hex}.tok"
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                if out is None:
                    where, name = fs.FileSystem.from_uri(folder)
                    where.create_dir(name, recursive=True)
                    out = where.open_output_stream(f"{name}/{path.rsplit('/', 1)[1]}")
                coded = encoder.encode([t or "" for t in part.column(1).to_pylist()])
                for ids in coded:
                    out.write(ids + tail)
                lengths.append(np.array([len(x) // encoder.width + 1 for x in coded], np.uint64))
                known = part.column(0).drop_null()
                n_null += part.num_rows - len(known)
                doc_ids.append(known.to_numpy(zero_copy_only=False))
        if out is None:
            return
        ends = np.cumsum(np.concatenate(lengths), dtype=np.uint64)
        ids = np.concatenate(doc_ids).astype(np.int64)
        first, last = (int(ids[0]), int(ids[-1])) if len(ids) else (0, 0)
        foot = struct.pack(_FOOT, encoder.width, len(ends), n_null, first, int(ends[-1]))
        foot += EliasFano.build((ids - first).astype(np.uint64)).to_bytes() + EliasFano.build(ends).to_bytes()
        out.write(foot + struct.pack("<Q", len(foot)) + _MAGIC)
        out.close()
        yield pa.RecordBatch.from_pydict(
            {
                "path": [path],
                "n_null": [n_null],
                "first_id": pa.array([first if len(ids) else None], pa.int64()),
                "last_id": pa.array([last if len(ids) else None], pa.int64()),
                "n_docs": [len(ends)],
                "n_ids": [int(ends[-1])],
            }
        )

    return run


def write(docs: DataFrame, tokenizer: str, folder: str | None = None, end_id: int = 0) -> DataFrame:
    """Encode ``docs(doc_id, text)`` into files in ascending doc_id order; returns the manifest.

    One range partition makes one file (null ids first; rows of one id are ordered by a hash of the text, and may go
    to several files), streamed, so memory is bounded by a batch and the file's boundaries. The manifest has one row for each file with
    ``start``, the ids in all files before it; files that a lost attempt left are not in it.
    ``folder`` must be one that all executors share; by default it is in shared scratch storage.
    A null text is an empty one. An empty table gives an empty manifest.
    """
    folder = folder or scratch_path(docs.sparkSession, "tokens")
    ordered = (
        docs.select(F.col("doc_id").cast("long"), "text")
        .withColumn("mix", F.xxhash64("text"))
        .repartitionByRange("doc_id", "mix")
        .sortWithinPartitions("doc_id", "mix")
        .drop("mix")
    )
    files = ordered.mapInArrow(
        _writer(tokenizer, folder, end_id), "path string, n_null long, first_id long, last_id long, n_docs long, n_ids long"
    )
    done = materialize(files, "manifest")
    # one row for each file, so this window is small beside the ids
    order = [F.desc(F.col("n_null") > 0), F.asc_nulls_first("first_id"), F.asc_nulls_first("last_id"), F.col("path")]
    before = Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    return done.withColumn("start", F.coalesce(F.sum("n_ids").over(before), F.lit(0)))


def read(manifest: DataFrame) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` of every document, from the files: each run of documents is found by selects.

    An empty manifest gives an empty result; repeated documents are separate rows.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, start in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                file, lo = TokenFile(path), 0
                for at in range(0, file.n_docs, 2048):
                    to = min(at + 2048, file.n_docs)
                    ends = file.ends.values(at, to)
                    begins = np.append(lo, ends[:-1])
                    raw = file.file.read_at(int(ends[-1] - lo) * file.width, lo * file.width)
                    wide = np.frombuffer(raw, f"<u{file.width}").astype("<u4")
                    sums = [zlib.crc32(x) for x in np.split(wide, ends[:-1] - lo)]
                    lo = int(ends[-1])
                    nulls = min(max(file.n_null - at, 0), to - at)
                    known = file.doc_ids.values(at + nulls - file.n_null, to - file.n_null) + file.first_id if nulls < to - at else []
                    ids = pa.concat_arrays([pa.nulls(nulls, pa.int64()), pa.array(known, pa.int64())])
                    columns = [ids, pa.array(begins + start), pa.array(ends - begins), pa.array(sums, pa.int64())]
                    yield pa.RecordBatch.from_arrays(columns, ["doc_id", "start", "n_tokens", "ids_crc32"])
                file.close()

    n = manifest.sparkSession.conf.get("spark.sql.shuffle.partitions")
    return (
        manifest.select("path", "start")
        .repartition(int(n), "path")
        .mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")
    )
