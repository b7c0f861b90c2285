"""Secret scans through nested encodings.

A text is the first layer of a worklist. Each layer is scanned, and whatever it wraps (URL percent
codes, Unicode escapes and character references, base64, and zlib or gzip data inside base64) becomes a
new layer, until no new layer appears. A layer knows for each of its characters which span
of the original text it came from, so a secret found in any layer is reported in original code points.
"""

from __future__ import annotations

import binascii
import codecs
import hashlib
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from groupflow.llm.worker_memory import tidy

# fixed values: the kinds in their order, their patterns, and the least length of what is tested
KINDS = ("assign", "access", "hex")
_ASSIGN = re.compile(
    r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII | re.IGNORECASE
)
_ACCESS = re.compile(r"AKIA[A-Z0-9]+")
_LEAST = (6, 20, 24)
# a run that is long enough is a match of its own, shorter runs fail: the same matches, found faster
_LONG_HEX = re.compile(r"[0-9a-f]{24,}")

_PERCENT = re.compile(r"(?:%[0-9A-Fa-f]{2})+")
_ESCAPE = re.compile(r"(?:\\u[0-9A-Fa-f]{4})+|\\x[0-9A-Fa-f]{2}|&#[0-9]{1,7};|&#[xX][0-9A-Fa-f]{1,6};")
# the shortest match has 12 bytes, so 16 characters of base64
_BASE64 = re.compile(r"[A-Za-z0-9+/_-]{16,}={0,2}")
_STRETCH = re.compile(
    rb"(?:[\t\n\r\x20-\x7e]|[\xc2-\xdf][\x80-\xbf]|[\xe0-\xef][\x80-\xbf]{2}|[\xf0-\xf4][\x80-\xbf]{3}){12,}"
)
# where gzip or zlib data may begin, in a run that has other characters before them
_PACKED = re.compile(
    b"\x1f\x8b\x08|"
    + b"|".join(
        re.escape(bytes([c])) + b"[" + b"".join(re.escape(bytes([f])) for f in range(256) if (c << 8 | f) % 31 == 0 and not f & 32) + b"]"
        for c in range(8, 128, 16)
    ),
    re.DOTALL,
)
# where a text may be cut: after a character that no pattern here has, or after a word in spaces that no match begins with
_CUT = re.compile(
    r"""[^A-Za-z0-9+/_.=\-"':\x20%\\&\#;]|(?<=\x20)[A-Za-z0-9+/_.-]+"""
    r"""(?<!password)(?<!passwd)(?<!secret)(?<!token)(?<!api_key)(?<!apikey)\x20(?!\x20)""",
    re.ASCII | re.IGNORECASE,
)
_STEP = 1 << 20


@dataclass(frozen=True)
class SecretParams:
    """``max_layer``: decompressed data are taken in steps of at most so many bytes (and of a MiB at most) and
    scanned in pieces, so that compression bombs are scanned to their end without being held in memory."""

    max_layer: int = 16_000_000


@dataclass
class _Layer:
    text: str
    start: np.ndarray | None  # original span of each character; None: the original itself
    end: np.ndarray | None

    def original(self, a: int, b: int) -> tuple[int, int]:
        if self.start is None:
            return a, b
        return int(self.start[a:b].min()), int(self.end[a:b].max())

    def spans(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Original spans of the layer's spans ``[a, b)``, none of them empty."""
        if self.start is None:
            return a, b
        return self.start[a], self.end[b - 1]


def scan(text: str) -> list[tuple[int, int, int]]:
    """``(start, kind number, end)`` of the matches in one layer, leftmost and non-overlapping per kind."""
    found = []
    for m in _ASSIGN.finditer(text):
        if m.end(2) - m.start(2) >= _LEAST[0]:
            found.append((m.start(), 0, m.end()))
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in _ACCESS.finditer(text) if m.end() - m.start() >= _LEAST[1]]
    found += [(m.start(), 2, m.end()) for m in _LONG_HEX.finditer(text)]
    return sorted(found)


def _substituted(layer: _Layer, pattern: re.Pattern, decode) -> _Layer | None:
    """The layer with each match of ``pattern`` replaced by what it encodes, all else kept in place."""
    parts, a, b, at = [], [], [], 0
    for m in pattern.finditer(layer.text):
        new = decode(m.group())
        if new is None:
            continue
        i, j = m.span()
        parts += (layer.text[at:i], new)
        a += (np.arange(at, i), np.full(len(new), i))
        b += (np.arange(at + 1, i + 1), np.full(len(new), j))
        at = j
    if not parts:
        return None
    n = len(layer.text)
    text = "".join(parts) + layer.text[at:]
    if not text:
        return None
    start, end = layer.spans(np.concatenate([*a, np.arange(at, n)]), np.concatenate([*b, np.arange(at + 1, n + 1)]))
    return _Layer(text, start, end)


def _percent(code: str) -> str | None:
    return bytes.fromhex(code.replace("%", "")).decode("utf-8", "replace")


def _escape(code: str) -> str | None:
    if code[0] == "&":
        value = int(code[3:-1], 16) if code[2] in "xX" else int(code[2:-1])
        return chr(value) if 0 < value < 0xD800 or 0xE000 <= value < 0x110000 else None
    if code[1] == "x":
        return chr(int(code[2:], 16))
    units = bytes.fromhex(code.replace("\\u", ""))
    return units.decode("utf-16-be", "replace")


def _unpacked(data: memoryview, step: int) -> Iterator[bytes]:
    """Decompressed zlib or gzip data with all members, in steps; ends where the data are damaged."""
    while len(data) and _PACKED.match(data):
        worker = zlib.decompressobj(47)
        try:
            while not worker.eof and (len(data) or worker.unconsumed_tail):
                out = worker.decompress(worker.unconsumed_tail or data, step)
                data = data[:0]
                if out:
                    yield out
                elif not worker.unconsumed_tail:
                    break
        except zlib.error:
            return
        data = worker.unused_data.lstrip(b"\0")  # the next member; gzip allows zeros between


def _pieces(steps: Iterator[bytes]) -> Iterator[str]:
    """The text of ``steps``, cut only where no match and nothing encoded can stand across, so that the pieces
    hold together what the whole text holds. A stretch without such a place is one piece, however long."""
    decoder = codecs.getincrementaldecoder("utf-8")("replace")
    parts: list[str] = []
    for out in steps:
        text = decoder.decode(out)
        edge = parts[-1][-256:] if parts else ""
        at = None
        for size in (4096, 65_536, len(edge) + len(text)):
            tail = (edge + text)[-size:]
            for m in _CUT.finditer(tail):
                at = m.end() - len(tail)
            if at is not None:
                break
        if at is None:
            parts.append(text)
            continue
        whole = "".join(parts) + text
        yield whole[: len(whole) + at]
        parts = [whole[len(whole) + at :]]
    if last := "".join(parts) + decoder.decode(b"", True):
        yield last


def _readable(data: bytes) -> str | None:
    try:
        text = data.decode("utf-8")
    except UnicodeDecodeError:
        return None
    odd = sum(not (c.isprintable() or c in "\n\r\t") for c in text)
    return text if text and odd * 20 <= len(text) else None


def _packed(layer: _Layer, step: int) -> Iterator[_Layer]:
    """Layers that stand in base64 runs, or in parts of them: a run is decoded from each of its first four characters,
    and where that is not readable as a whole, its readable stretches are layers."""
    for m in _BASE64.finditer(layer.text):
        core = m.group().rstrip("=").replace("-", "+").replace("_", "/")
        for phase in range(4):
            part = core[phase:]
            if len(part) % 4 == 1:
                part = part[:-1]
            if len(part) < 16:
                break
            data = binascii.a2b_base64(part + "=" * (-len(part) % 4))
            for x in _PACKED.finditer(data):
                a, b = layer.original(*m.span())
                for text in _pieces(_unpacked(memoryview(data)[x.start() :], step)):
                    yield _Layer(text, np.broadcast_to(a, len(text)), np.broadcast_to(b, len(text)))
            whole = _readable(data)
            for at, text in [(0, whole)] if whole is not None else ((x.start(), _readable(x.group())) for x in _STRETCH.finditer(data)):
                if text is None:
                    continue
                width = np.array([len(c.encode()) for c in text])
                last = at + np.cumsum(width)
                first = last - width
                i = m.start() + phase + first * 4 // 3
                j = np.minimum(m.start() + phase + (last * 4 + 2) // 3, m.end())
                yield _Layer(text, *layer.spans(i, j))


def _wrapped(layer: _Layer, step: int) -> Iterator[_Layer | None]:
    """The layers that a layer wraps, one at a time."""
    if "%" in layer.text:
        yield _substituted(layer, _PERCENT, _percent)
    if "\\" in layer.text or "&#" in layer.text:
        yield _substituted(layer, _ESCAPE, _escape)
    yield from _packed(layer, step)


def _key(layer: _Layer) -> tuple[bytes, int, int]:
    digest = hashlib.blake2b(layer.text.encode("utf-8", "surrogatepass"), digest_size=16).digest()
    return digest, int(layer.start[0]), int(layer.end[-1])


def find(text: str | None, p: SecretParams = SecretParams()) -> tuple[list, list, bool]:
    """Base spans, all spans (both sorted ``(start, kind number, end)``) and whether a bound was met: none is, every
    layer is scanned to its end."""
    if not text:
        return [], [], False
    base = scan(text)
    every = set(base)
    step = max(1, min(p.max_layer, _STEP))
    work = [_wrapped(_Layer(text, None, None), step)]
    seen: set[tuple[bytes, int, int]] = set()
    while work:
        layer = next(work[-1], work)
        if layer is work:
            work.pop()
            continue
        if layer is None or (key := _key(layer)) in seen:  # a layer that leads back to a seen one is not entered again
            continue
        seen.add(key)
        for a, kind, b in scan(layer.text):
            lo, hi = layer.original(a, b)
            every.add((lo, kind, hi))
        work.append(_wrapped(layer, step))
    return base, sorted(every), False


def _joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


def scan_documents(docs: DataFrame, p: SecretParams = SecretParams()) -> DataFrame:
    """``doc_id, n_assign, n_access, n_hex, base_spans, spans, bounded`` for each row.

    The counts are of base spans. A null or empty text has no span. Rows are independent; other
    columns are not read.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = [find(t.as_py(), p) for t in batch.column(1)]
            counts = [pa.array([sum(s[1] == k for s in x[0]) for x in out], pa.int64()) for k in range(3)]
            texts = [pa.array([_joined(x[i]) for x in out], pa.string()) for i in (0, 1)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *counts, *texts, pa.array([x[2] for x in out], pa.bool_())],
                ["doc_id", "n_assign", "n_access", "n_hex", "base_spans", "spans", "bounded"],
            )

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(
        run, "doc_id long, n_assign long, n_access long, n_hex long, base_spans string, spans string, bounded boolean"
    )


def redact_text(text: str | None, mark: str = "[SECRET]", p: SecretParams = SecretParams()) -> str | None:
    """The text with every found span, overlapping ones merged, replaced by ``mark``."""
    spans = find(text, p)[1]
    if not spans:
        return text
    out, at, reach = [], 0, 0
    for a, _, b in spans:
        if a >= reach:
            out += (text[at:a], mark)
        reach = max(reach, b)
        at = reach
    return "".join(out) + text[at:]


def redact(docs: DataFrame, p: SecretParams = SecretParams()) -> DataFrame:
    """``docs`` with secrets in ``text`` replaced; ``n_chars``, if there, follows. Rows are all kept."""
    names, at = docs.columns, docs.columns.index("text")
    length = names.index("n_chars") if "n_chars" in names else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns = list(batch.columns)
            texts = [redact_text(t.as_py(), p=p) for t in columns[at]]
            columns[at] = pa.array(texts, pa.string())
            if length is not None:
                changed = [n.as_py() if t is None else len(t) for n, t in zip(columns[length], texts)]
                columns[length] = pa.array(changed, columns[length].type)
            yield pa.RecordBatch.from_arrays(columns, names)

    return docs.mapInArrow(tidy(run), docs.schema)
