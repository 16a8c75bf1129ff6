"""Secret scans through nested encodings.

The text is scanned by plain patterns; then a worklist unwraps percent escapes, backslash escapes,
base64 and compressed data, layer by layer, and scans each layer with the same patterns. A layer
whose content was seen on the way to it is not opened again, so cycles end.

Two kinds of layer. Escapes of a text leave a text whose signs have places of their own, one sign an
escape. All below base64 or compressed data stands at the place of the encoded signs; it is read as
a stream that can be read again, in windows, with every decoder's state carried from window to
window, so that what a layer holds is found alike at any size.
"""

from __future__ import annotations

import binascii
import hashlib
import re
import zlib
from array import array
from bisect import bisect_right
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsecert.llm.common import load, slices

KINDS = ("assign", "access", "hex")
#: Fixed patterns of the contract.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{16,}")
MOST_HIDDEN = 1 << 20  # bytes of a hidden layer's window
OVERLAP = 4096  # what a window repeats of the one before, blanks in a row counted once: far more than a pattern needs to match

#: Percent escapes of percent signs are undone together with what they escape.
PERCENT = re.compile(r"%(?:25)*([0-9A-Fa-f]{2})")
ESCAPE = re.compile(r"""\\(?:u\{([0-9A-Fa-f]{1,6})\}|u([0-9A-Fa-f]{4})|x([0-9A-Fa-f]{2})|U([0-9A-Fa-f]{8})|(["'/\\nrt]))""")
SIMPLE = {"n": "\n", "r": "\r", "t": "\t"}
#: A run of base64, and one that is broken into lines.
LEAST_RUN = 20
RUN = re.compile(r"[A-Za-z0-9+/_-]{20,}+={0,2}")
WRAPPED = re.compile(r"(?<![A-Za-z0-9+/_-])(?:[A-Za-z0-9+/_-]{20,}+\r?\n[\t ]*+)+[A-Za-z0-9+/_-]++={0,2}")
#: How gzip and zlib data begin.
MAGIC = re.compile(rb"\x1f\x8b\x08|\x78[\x01\x5e\x9c\xda]")
MAGIC_TEXT = re.compile("\x1f\x8b\x08|\x78[\x01\x5e\x9c\xda]")

_PERCENT, _ESCAPE = re.compile(PERCENT.pattern.encode()), re.compile(ESCAPE.pattern.encode())
#: What may go on as an escape beyond the end of a window.
_OPEN = {_PERCENT: re.compile(rb"%(?:25)*+[0-9A-Fa-f]?\Z|%(?:25)+\Z"), _ESCAPE: re.compile(rb"\\(?:[uxU]\{?[0-9A-Fa-f]{0,8})?\Z")}
_SPACES = re.compile(rb"\x20{2,}")
_BREAK = re.compile(rb"[\r\n]+[\t ]*")
_OPEN_BREAK = re.compile(rb"[\r\n][\t ]*\Z")
_LONG = re.compile(rb"[A-Za-z0-9+/_-]{20,}")
_LEADING = re.compile(rb"[A-Za-z0-9+/_-]*")
_DIGITS64 = b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_-"
_PLAIN64 = bytes.maketrans(b"-_", b"+/")


def scan(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the plain patterns' spans, by start, then kind."""
    out = []
    if ":" in text or "=" in text:
        out += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 12]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 18]
    out += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(out)


# ---- decoded texts whose signs have places of their own


class Origin:
    """Where the signs of a text come from: escapes, and stretches between them that were taken over."""

    def __init__(self, above: Origin | None):
        self.above, self.at, self.starts, self.ends = above, array("q"), array("q"), array("q")

    def add(self, at: int, start: int, end: int) -> None:
        self.at.append(at)
        self.starts.append(start)
        self.ends.append(end)

    def _of(self, i: int) -> tuple[int, int]:
        k = bisect_right(self.at, i) - 1
        if k < 0:
            return i, i + 1
        if self.at[k] == i:
            return self.starts[k], self.ends[k]
        start = self.ends[k] + i - self.at[k] - 1
        return start, start + 1

    def place(self, start: int, end: int) -> tuple[int, int]:
        start, end = self._of(start)[0], self._of(end - 1)[1]
        return self.above.place(start, end) if self.above else (start, end)


def _sign(m: re.Match) -> str:
    """What an escape stands for, in one sign."""
    if m.re is PERCENT:
        return chr(int(m[1], 16))
    if m[5]:
        return SIMPLE.get(m[5], m[5])
    code = int(m[1] or m[2] or m[3] or m[4], 16)
    return chr(code) if code < 0x110000 else "\ufffd"


def _undone(text: str, escape: re.Pattern, above: Origin | None) -> tuple[str, Origin]:
    out, origin, at, length = [], Origin(above), 0, 0
    for m in escape.finditer(text):
        out += (text[at : m.start()], _sign(m))
        length += m.start() - at
        origin.add(length, m.start(), m.end())
        length += 1
        at = m.end()
    out.append(text[at:])
    return "".join(out), origin


def _mark(data: bytes) -> bytes:
    return hashlib.blake2b(data, digest_size=16).digest()


@dataclass
class Window:
    """Decoded signs; what is found in them stands at (low, high), or where their origin says."""

    text: str
    low: int = 0
    high: int = 0
    origin: Origin | None = None

    def place(self, start: int, end: int) -> tuple[int, int]:
        return self.origin.place(start, end) if self.origin else (self.low, self.high)


class Text:
    """A document (no origin), or what undoing its escapes left."""

    def __init__(self, text: str, origin: Origin | None, seen: set[bytes]):
        self.text, self.origin, self.seen = text, origin, seen

    def windows(self) -> Iterator[Window]:
        if self.origin:
            yield Window(self.text, origin=self.origin)

    def is_new(self) -> bool:
        mark = _mark(self.text.encode("utf-8", "surrogatepass"))
        new = mark not in self.seen
        self.seen.add(mark)
        return new

    def below(self) -> Iterator[Text | Hidden]:
        text, place = self.text, self.origin.place if self.origin else lambda start, end: (start, end)
        for sign, escape in (("%", PERCENT), ("\\", ESCAPE)):
            if sign in text and escape.search(text):
                yield Text(*_undone(text, escape, self.origin), self.seen)
        for pattern in (RUN, WRAPPED):
            for m in pattern.finditer(text):
                data, seen = m.group().encode(), set()
                for skip in range(4):
                    yield Hidden(lambda data=data, skip=skip: _from_base64(lambda: _pieces(data), skip), *place(*m.span()), seen)
        if self.origin and MAGIC_TEXT.search(text):
            data = text.encode("latin-1", "replace")
            for start, end in _packed(data):
                yield Hidden(lambda part=data[start:end]: _inflated(lambda: _pieces(part)), *place(start, end), set())


# ---- layers below base64 and compression, as streams


def _pieces(data: bytes) -> Iterator[bytes]:
    for i in range(0, len(data), MOST_HIDDEN):
        yield data[i : i + MOST_HIDDEN]


def _unescaped(read: Callable[[], Iterator[bytes]], escape: re.Pattern) -> Iterator[bytes]:
    """A stream with its escapes undone; one that is cut by a window's end waits for the next window."""

    def sign(m: re.Match) -> bytes:
        if escape is _PERCENT:
            return bytes([int(m[1], 16)])
        if m[5]:
            return SIMPLE.get(m[5].decode(), m[5].decode()).encode()
        code = int(m[1] or m[2] or m[3] or m[4], 16)
        return bytes([code]) if code < 256 else b"?"

    held = b""
    for data in read():
        data = held + data
        rest = _OPEN[escape].search(data)
        cut = rest.start() if rest and len(data) - rest.start() < MOST_HIDDEN else len(data)
        held = data[cut:]
        yield escape.sub(sign, data[:cut])
    yield escape.sub(sign, held)


def _bytes_of(run: bytes) -> bytes:
    run = run[: len(run) - (len(run) % 4 == 1)]
    return binascii.a2b_base64(run.translate(_PLAIN64) + b"=" * (-len(run) % 4))


def _from_base64(read: Callable[[], Iterator[bytes]], skip: int) -> Iterator[bytes]:
    """What the stream's runs of base64 hold if `skip` signs before them belong to something else.

    Line ends are left out, so that a run goes on in the next line. A run's end is a line end.
    """
    run, begun, in_break = b"", False, False  # run: signs of the open run that aren't decoded yet

    def ended() -> bytes:
        if not begun and len(run) < LEAST_RUN:
            return b""
        return _bytes_of(run if begun else run[skip:]) + b"\n"

    for data in read():
        joined = _BREAK.sub(b"", data.lstrip(b"\t ") if in_break else data)
        in_break = bool(_OPEN_BREAK.search(data)) or in_break and not data.strip(b"\t ")
        lead = _LEADING.match(joined).end()
        run += joined[:lead]
        out = []
        if lead < len(joined):
            out.append(ended())
            tail = max(lead, len(joined.rstrip(_DIGITS64)))
            out += [_bytes_of(m.group()[skip:]) + b"\n" for m in _LONG.finditer(joined, lead, tail)]
            run, begun = joined[tail:], False
        if len(run) > OVERLAP:
            if not begun:
                run, begun = run[skip:], True
            whole = len(run) // 4 * 4
            out.append(_bytes_of(run[:whole]))
            run = run[whole:]
        yield b"".join(out)
    yield ended()


STEP = 1 << 14


def _members(read: Callable[[], Iterator[bytes]]) -> Iterator[tuple[bytes, int, int]]:
    """(unpacked bytes, start, end) of gzip and zlib data anywhere in a stream, all members; end is -1 until one's end.

    Data that turns out to be broken is searched again from the sign after its start, or from the
    window it broke in if it began in an earlier one.
    """
    engine, kept, passed, begun = None, b"", 0, 0  # passed: bytes before `data`
    for piece in read():
        data, at = kept + piece, 0
        kept = b""
        here = engine is None  # whether the member began in this window
        while True:
            if engine is None:
                m = MAGIC.search(data, at)
                if not m:
                    kept = data[max(at, len(data) - 2) :]
                    break
                at, here, engine = m.start(), True, zlib.decompressobj(47)
                begun = passed + at
            broken = False
            try:
                while at < len(data) and not engine.eof:
                    feed = data[at : at + STEP]
                    at += len(feed)
                    while True:
                        got = engine.decompress(feed, MOST_HIDDEN)
                        if got:
                            yield got, begun, -1
                        feed = engine.unconsumed_tail
                        if engine.eof or not feed and len(got) < MOST_HIDDEN:
                            break
            except zlib.error:
                broken = True
            if broken:
                at, engine = (begun - passed + 1 if here else 0), None
            elif engine.eof:
                at -= len(engine.unused_data)
                engine = None
                yield b"", begun, passed + at
            else:
                break
        passed += len(data) - len(kept)
    if engine is not None:
        yield b"", begun, passed


def _inflated(read: Callable[[], Iterator[bytes]]) -> Iterator[bytes]:
    """What the members hold; those in a row, or parted by zeros as padding, are one text."""
    for got, _, _ in _members(read):
        if got:
            yield got


def _packed(data: bytes) -> Iterator[tuple[int, int]]:
    """Stretches of data that hold compressed members in a row."""
    start = stop = -1
    for _, begun, end in _members(lambda: _pieces(data)):
        if end < 0:
            continue
        if start >= 0 and data[stop:begun].strip(b"\0"):
            yield start, stop
            start = -1
        start, stop = (begun if start < 0 else start), end
    if start >= 0:
        yield start, stop


class Hidden:
    """A layer as a stream of bytes that can be read again. A small one is kept while the layers below it are read."""

    def __init__(self, read: Callable[[], Iterator[bytes]], low: int, high: int, seen: set[bytes]):
        self.read, self.low, self.high, self.seen = read, low, high, seen
        self.mark = b""
        self.holds: set[str] = set()

    def windows(self) -> Iterator[Window]:
        mark, tail, kept, size = hashlib.blake2b(digest_size=16), b"", [], 0
        for data in self.read():
            if not data:
                continue
            mark.update(data)
            size += len(data)
            kept = [*kept, data] if kept is not None and size <= MOST_HIDDEN else None
            both = tail + data
            joined = _BREAK.sub(b"", both)
            for name, pattern, where in (("percent", _PERCENT, both), ("escape", _ESCAPE, both), ("packed", MAGIC, both), ("base64", _LONG, joined)):
                if name not in self.holds and pattern.search(where):
                    self.holds.add(name)
            yield Window(_SPACES.sub(b" ", both).decode("latin-1"), self.low, self.high)
            tail = _SPACES.sub(b" ", both)[-OVERLAP:]
        self.mark = mark.digest()
        if kept is not None:
            self.read = lambda: iter(kept)

    def is_new(self) -> bool:
        """Asked after the windows were read."""
        new = self.mark not in self.seen
        self.seen.add(self.mark)
        return new

    def below(self) -> Iterator[Hidden]:
        read, rest = self.read, (self.low, self.high, self.seen)
        if "percent" in self.holds:
            yield Hidden(lambda: _unescaped(read, _PERCENT), *rest)
        if "escape" in self.holds:
            yield Hidden(lambda: _unescaped(read, _ESCAPE), *rest)
        if "base64" in self.holds:
            for skip in range(4):
                yield Hidden(lambda skip=skip: _from_base64(read, skip), *rest)
        if "packed" in self.holds:
            yield Hidden(lambda: _inflated(read), *rest)


def _opened(text: str) -> Iterator[Window]:
    """The windows of all layers below a text.

    The worklist holds what is left to unwrap at each depth, so one window a depth is in memory,
    also where compressed data unfolds into many.
    """
    work: list[Iterator[Text | Hidden]] = [Text(text, None, set()).below()]
    while work:
        layer = next(work[-1], None)
        if layer is None:
            work.pop()
            continue
        yield from layer.windows()
        if layer.is_new():
            work.append(layer.below())


def find_secrets(text: str) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]:
    """Base spans and all spans, as (start, kind, end)."""
    base = scan(text)
    every = set(base)
    for window in _opened(text):
        for start, kind, end in scan(window.text):
            low, high = window.place(start, end)
            every.add((low, kind, high))
    return base, sorted(every)


def joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[kind]}:{start}:{end}" for start, kind, end in spans)


def _scanned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_layers_spans"]
    for batch in slices(batches, "_text"):
        counts: list[list[int]] = [[], [], []]
        digests, spans, added = [], [], []
        for text in batch.column("_text").to_pylist():
            base, every = find_secrets(text)
            for k in range(3):
                counts[k].append(sum(1 for s in base if s[1] == k))
            digests.append(hashlib.sha256(joined(base).encode()).hexdigest())
            spans.append(joined(every))
            added.append(len(every) - len(base))
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *[pa.array(c, pa.int64()) for c in counts], pa.array(digests, pa.string()), pa.array(spans, pa.string()), pa.array(added, pa.int64())], names=names)


def scan_documents(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """One row per row of docs: counts and digest of the plain spans, and all spans.

    Null texts count as empty; ids may be null or repeat; an empty table gives an empty result;
    further columns of docs are ignored.
    """
    narrow = docs.select(F.col(key).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("_text"))
    kind = narrow.schema["doc_id"].dataType.simpleString()
    return narrow.mapInArrow(_scanned, f"doc_id {kind}, n_assign bigint, n_access bigint, n_hex bigint, base_sha256 string, spans string, n_layers_spans bigint")


def op9_layered_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_documents(load(spark, sf_dir, "documents"))
