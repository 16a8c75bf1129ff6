"""Hierarchical residual packing of token sequences.

Documents are tokenized once; pieces of full length are sequences already. The rest is packed in
rounds: partitions put items into the fullest bin that holds them, bins that nothing could join are
final, and the others go on, as items, to a round with fewer partitions.
"""

from __future__ import annotations

import bisect
import json
import re
import zlib
from array import array
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparsecert.llm.common import load, slices, staged

#: The special string of the vocabulary with its id, and the id that ends a document.
SPECIAL, SPECIAL_ID, END_ID = "<|endoftext|>", 50256, 0
CAPACITY = 2048
FAN_IN = 8


#: What the vocabulary's split pattern takes for white space; a run of so many blanks is cut out, as the pattern's engine can't hold millions.
BLANK_RUN = re.compile(r"[\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]{10000,}")


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def byte_of_sign() -> dict[str, int]:
    """The signs that stand for bytes in a byte-level vocabulary: printable Latin-1 for itself, the others from 256 on."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    signs = {chr(b): b for b in plain}
    return signs | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in plain)}


class Encoder:
    """The ids that `tokenizers` gives for a byte-level BPE file, special string included."""

    def __init__(self, path: str):
        import public_tokenizers
        import tiktoken

        with open(path, encoding="utf-8") as f:
            vocabulary = json.load(f)["model"]["vocab"]
        signs = byte_of_sign()
        ranks = {bytes(signs[c] for c in token): i for token, i in vocabulary.items() if i != SPECIAL_ID}
        self.plain = tiktoken.Encoding("byte_bpe_50k", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

    def ids(self, text: str) -> list[int]:
        if SPECIAL not in text:
            return self._ordinary(text)
        out: list[int] = []
        for i, part in enumerate(text.split(SPECIAL)):
            if i:
                out.append(SPECIAL_ID)
            out += self._ordinary(part)
        return out

    def _ordinary(self, text: str) -> list[int]:
        """Without the special string. The pattern parts a text where a run of blanks begins, and before the
        run's last blank if more follows; so a long run is a piece that can be encoded by itself."""
        out: list[int] = []
        at = 0
        for m in BLANK_RUN.finditer(text) if len(text) >= 10_000 else ():
            stop = m.end() if m.end() == len(text) else m.end() - 1
            out += self.plain.encode_ordinary(text[at : m.start()])
            out += self.plain._encode_single_piece(text[m.start() : stop])
            at = stop
        out += self.plain.encode_ordinary(text[at:] if at else text)
        return out


def pieces_of(length: int, capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces: the first one takes what full pieces leave."""
    if length <= capacity:
        return [(0, length)]
    first = length % capacity or capacity
    return [(0, first), *((s, capacity) for s in range(first, length, capacity))]


PIECE_COLUMNS = ("piece int", "start bigint", "length bigint", "ids_crc32 bigint")


def _tokenized(ranks_path: str, capacity: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder(ranks_path)
        for batch in slices(batches, "_text"):
            at, piece_no, starts, lengths, sums = [], [], [], [], []
            for i, text in enumerate(batch.column("_text").to_pylist()):
                ids = array("I", encoder.ids(text))
                ids.append(END_ID)
                raw = memoryview(ids.tobytes())
                for piece, (start, length) in enumerate(pieces_of(len(ids), capacity)):
                    at.append(i)
                    piece_no.append(piece)
                    starts.append(start)
                    lengths.append(length)
                    sums.append(zlib.crc32(raw[4 * start : 4 * (start + length)]))
            taken = pa.array(at, pa.int64())
            longs = [pa.array(c, pa.int64()) for c in (starts, lengths, sums)]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(taken), batch.column("_row").take(taken), pa.array(piece_no, pa.int32()), *longs], names=["doc_id", "_row", "piece", "start", "length", "ids_crc32"])

    return run


class Bins:
    """Open bins by the room they have left; an item goes to the fullest bin that holds it."""

    def __init__(self, capacity: int):
        self.capacity = capacity
        self.by_room: dict[int, list[int]] = {}
        self.rooms: list[int] = []
        self.members: list[list[int]] = []

    def put(self, item: int, size: int) -> None:
        at = bisect.bisect_left(self.rooms, size)
        if at < len(self.rooms):
            room = self.rooms[at]
            bin_ = self.by_room[room].pop()
            if not self.by_room[room]:
                del self.by_room[room], self.rooms[at]
        else:
            room, bin_ = self.capacity, len(self.members)
            self.members.append([])
        self.members[bin_].append(item)
        left = room - size
        if left:
            if left not in self.by_room:
                self.by_room[left] = []
                bisect.insort(self.rooms, left)
            self.by_room[left].append(bin_)


def best_fit(sizes: list[int], capacity: int = CAPACITY) -> list[list[int]]:
    """Bins, as lists of places in sizes; larger items first."""
    bins = Bins(capacity)
    for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
        bins.put(i, sizes[i])
    return bins.members


def _packed(capacity: int, most_items: int):
    """Best-fit over up to most_items items at a time: bins of (size, members as bytes of row-piece pairs)."""

    def pack(sizes: list[int], members: list[bytes]) -> pa.RecordBatch:
        bins = best_fit(sizes, capacity)
        return pa.RecordBatch.from_arrays([pa.array([sum(sizes[i] for i in b) for b in bins], pa.int64()), pa.array([b"".join(members[i] for i in b) for b in bins], pa.binary())], names=["size", "members"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sizes: list[int] = []
        members: list[bytes] = []
        for batch in batches:
            sizes += batch.column("size").to_pylist()
            members += batch.column("members").to_pylist()
            if len(sizes) >= most_items:
                yield pack(sizes, members)
                sizes, members = [], []
        if sizes:
            yield pack(sizes, members)

    return run


def _unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["_r", "_p", "sequence_id", "offset"]
    for batch in batches:
        out: list[list[int]] = [[] for _ in names]
        for sequence, members in zip(batch.column("sequence_id").to_pylist(), batch.column("members").to_pylist(), strict=True):
            offset, triples = 0, memoryview(members).cast("q")
            for i in range(0, len(triples), 3):
                for column, value in zip(out, (triples[i], triples[i + 1], sequence, offset), strict=True):
                    column.append(value)
                offset += triples[i + 2]
        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in out], names=names)


def _members(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows, pieces, lengths = (batch.column(c).to_pylist() for c in ("_row", "piece", "length"))
        packed = [array("q", x).tobytes() for x in zip(rows, pieces, lengths, strict=True)]
        yield pa.RecordBatch.from_arrays([batch.column("length").cast(pa.int64()), pa.array(packed, pa.binary())], names=["size", "members"])


def pack_items(items: DataFrame, capacity: int = CAPACITY, most_items: int = 200_000) -> DataFrame:
    """items: _row, piece, length. Returns (size, members) bins; no task holds over most_items items.

    Each round has an eighth of the partitions before it, or what most_items asks for. A bin is final
    when the smallest bin no longer fits it; all are after the round of one partition, or when a
    round hardly saves bins.
    """
    bins = "size bigint, members binary"
    narrow = items.select("_row", "piece", "length")
    done = [staged(narrow.filter(F.col("length") == capacity).mapInArrow(_members, bins), "full")]
    rest = narrow.filter(F.col("length") < capacity).mapInArrow(_members, bins)
    count = narrow.filter(F.col("length") < capacity).count()
    parts = max(1, -(-count // min(most_items, 20_000)))
    while True:
        # dealt evenly, so each partition gets small items to fill gaps with
        packed = staged(rest.repartition(parts).mapInArrow(_packed(capacity, most_items), bins), "bins")
        least, made = packed.agg(F.min("size"), F.count(F.lit(1))).first()
        if parts == 1 or not made:
            return _union([*done, packed])
        is_open = (F.lit(capacity) - F.col("size")) >= least
        still = packed.filter(is_open).count()
        if not still or made > 0.999 * count:
            return _union([*done, packed])
        done.append(packed.filter(~is_open))
        rest, count, parts = packed.filter(is_open), still, max(1, parts // FAN_IN, -(-still // most_items))


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def pack(docs: DataFrame, text: str = "text", key: str = "doc_id", vocabulary: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    Null and empty texts are a document of one end id. Rows that repeat an id are packed as rows of
    their own. An empty table gives an empty result; further columns of docs are ignored.
    """
    keyed = docs.select(F.col(key).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("_text")).withColumn("_row", F.monotonically_increasing_id())
    schema = ", ".join((f"doc_id {keyed.schema['doc_id'].dataType.simpleString()}", "_row bigint", *PIECE_COLUMNS))
    pieces = staged(keyed.mapInArrow(_tokenized(vocabulary or default_vocabulary(), capacity), schema), "pieces")
    bins = staged(pack_items(pieces, capacity).withColumn("sequence_id", F.monotonically_increasing_id()), "sequences")
    places = bins.mapInArrow(_unpacked, "_r bigint, _p bigint, sequence_id bigint, offset bigint")
    joined = pieces.join(places, (F.col("_row") == F.col("_r")) & (F.col("piece").cast("bigint") == F.col("_p")))
    return joined.select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


def op8_hierarchical_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(load(spark, sf_dir, "documents"))
