"""Which values of a document occur in other documents too: an exchange in blocks and back.

Documents are dealt to blocks of bounded bytes by a hash of doc_id and text, so that rows without doc_id, or with one that
repeats, spread as well; rows that are equal in both share a block. A block sends each of its
values (64-bit hashes) to the bucket that the value names, four bytes and a count each, once
however often the block's documents hold it. A bucket sums the counts and answers each
block with those of its values that at least two documents hold, and how many do, as a class.
So no value needs one task for all its holders, and nothing but arrays of numbers travels.

Nobody sends more than FAN messages. Up to FAN blocks they go straight to the buckets; beyond, they pass relays in
as many steps as max(blocks, buckets) has digits to the base FAN: a relay of step i stands for a run of FAN**i blocks
and the buckets that are alike in their last i digits, holds about one block's values, and hands them on by the next
digit; answers take the same way back. So messages a step grow with the number of blocks, not with its square.

A value is known by its bucket and 32 further bits: two values may be taken for one, which makes a
value seem shared that is not. Callers check what they find with the bytes or whole hashes.
"""

from __future__ import annotations

import math
import struct
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fairlink.llm.common import give_back, kept, text_or_empty

BLOCK_BYTES = 4_000_000
BLOCKS_PER_BUCKET = 3
SLICE_BYTES = 500_000
FAN = 8192
#: a, b: the relay, bucket (a is 0) or block (b is 0) that a message is for.
LETTERS = "a long, b long, payload binary"


@dataclass(frozen=True)
class Exchange:
    """How many blocks and buckets there are, and the steps between them."""

    blocks: int
    buckets: int
    fan: int = FAN

    @property
    def steps(self) -> int:
        n = 1
        while self.fan**n < max(self.blocks, self.buckets):
            n += 1
        return n

    def letters(self, step: int, block: np.ndarray, bucket: np.ndarray, *columns: np.ndarray) -> pa.Table:
        """Rows (their block, bucket and columns) as messages to where they are after `step` steps."""
        size = self.fan**step
        a, b = block.astype(np.int64) // size, bucket.astype(np.int64) % size
        order = np.lexsort((b, a))
        a, b = a[order], b[order]
        starts = np.flatnonzero(np.r_[True, (a[1:] != a[:-1]) | (b[1:] != b[:-1])]) if len(a) else np.zeros(0, np.int64)
        stops = np.r_[starts[1:], len(a)][: len(starts)]
        ends, rest = [c[order].astype(np.int32) for c in (block, bucket)], [c[order] for c in columns]
        rows = []
        for i, j in zip(starts, stops, strict=True):
            short = [c[i : i + 1] if (c[i:j] == c[i]).all() else c[i:j] for c in ends]
            rows.append(packed(np.array([j - i]), *short, *(c[i:j] for c in rest)))
        return pa.table({"a": pa.array(a[starts], pa.int64()), "b": pa.array(b[starts], pa.int64()), "payload": pa.array(rows, pa.binary())})

    def relayed(self, messages: DataFrame, *kinds: str, back: bool = False) -> DataFrame:
        """Messages after the first step, or of the answers, brought to the last."""
        relay = lambda step: lambda table: self.letters(step, *opened(table, *kinds))
        for step in range(self.steps - 2, -1, -1) if back else range(2, self.steps + 1):
            messages = messages.groupBy("a", "b").applyInArrow(relay(step), LETTERS)
        return messages


def opened(table: pa.Table, *kinds: str) -> list[np.ndarray]:
    """Block, bucket and columns of a table of messages; kinds: types of the columns, as u4 or 80u1 for rows of bytes."""
    parts = [unpacked(x) for x in table.column("payload").to_pylist()]
    sizes = [int(p[0][0]) for p in parts]
    out = []
    for i, kind in enumerate(("i4", "i4", *kinds)):
        width, _, base = kind.rpartition("u1") if kind.endswith("u1") and kind != "u1" else ("", "", "")
        shape = (int(width),) if width else ()
        none = np.zeros((0, *shape), "u1" if width else kind)
        if i < 2:
            out.append(np.concatenate([none, *(np.broadcast_to(p[1 + i], n) for p, n in zip(parts, sizes, strict=True))]).astype(np.int64))
        else:
            out.append(np.concatenate([none, *(p[1 + i].reshape(-1, *shape) if width else p[1 + i] for p in parts)]))
    return out


def packed(*arrays: np.ndarray) -> bytes:
    """Arrays as one compressed value."""
    data = b"".join(struct.pack("<4sQ", a.dtype.str.encode().ljust(4), a.nbytes) + np.ascontiguousarray(a).tobytes() for a in arrays)
    return zstandard.ZstdCompressor(level=1).compress(data)


def unpacked(value: bytes) -> list[np.ndarray]:
    data, at, out = zstandard.ZstdDecompressor().decompress(value), 0, []
    while at < len(data):
        kind, size = struct.unpack_from("<4sQ", data, at)
        at += 12
        out.append(np.frombuffer(data, np.dtype(kind.decode().strip()), size // np.dtype(kind.decode().strip()).itemsize, at))
        at += size
    return out


def deal(docs: DataFrame, carry: tuple[str, ...] = (), block_bytes: int = BLOCK_BYTES, fan: int = FAN) -> tuple[DataFrame, Exchange]:
    """(block, doc_id, text, carried columns) and the exchange between so many blocks."""
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = max(1, math.ceil(total / block_bytes))
    dealt = docs.select(F.pmod(F.xxhash64("doc_id", "text"), F.lit(blocks)).cast("long").alias("block"), "doc_id", text_or_empty().alias("text"), *carry)
    return dealt, Exchange(blocks, max(1, math.ceil(blocks / BLOCKS_PER_BUCKET)), fan)


def chunks(table: pa.Table, *names: str, size: int = SLICE_BYTES) -> Iterator[tuple[list, ...]]:
    """Rows of the table in lists whose texts have about so many bytes together."""
    part: list[tuple] = []
    held = 0
    for batch in table.select(["text", *names]).to_batches(max_chunksize=128):
        for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            part.append(row)
            held += len(row[0])
            if held >= size:
                yield tuple(map(list, zip(*part, strict=True)))
                part, held = [], 0
    if part:
        yield tuple(map(list, zip(*part, strict=True)))


def code(values: np.ndarray, buckets: int) -> np.ndarray:
    """What is left of a value after the exchange."""
    n = np.uint64(buckets)
    return ((values // n) & np.uint64(0xFFFFFFFF)) * n + values % n


def shared(dealt: DataFrame, values: Callable[[list[str]], list[np.ndarray]], exchange: Exchange) -> DataFrame:
    """Messages to each block (a) with its shared values; values gives each text's distinct ones."""
    buckets = exchange.buckets

    def send(key: tuple, table: pa.Table) -> pa.Table:
        kept("blocks", dict)
        found = [v for texts, *_ in chunks(table) for v in values(texts)]
        every, count = np.unique(np.concatenate(found) if found else np.zeros(0, np.uint64), return_counts=True)
        bucket = (every % np.uint64(buckets)).astype(np.int64)
        rest = ((every // np.uint64(buckets)) & np.uint64(0xFFFFFFFF)).astype(np.uint32)
        sent = exchange.letters(1, np.full(len(every), key[0].as_py()), bucket, rest, np.minimum(count, 65535).astype(np.uint16))
        give_back()
        return sent

    def answer(key: tuple, table: pa.Table) -> pa.Table:
        block, bucket, rest, count = opened(table, "u4", "u2")
        order = np.argsort(rest, kind="stable")
        ranked = rest[order]
        starts = np.flatnonzero(np.r_[True, ranked[1:] != ranked[:-1]])
        sums = np.add.reduceat(count[order].astype(np.int64), starts)
        each = np.empty(len(rest), np.int64)
        each[order] = np.repeat(sums, np.diff(np.r_[starts, len(ranked)]))
        many = np.flatnonzero(each > 1)
        grade = np.minimum(255, np.log2(each[many]) * 4).astype(np.uint8)
        told = exchange.letters(exchange.steps - 1, block[many], bucket[many], rest[many], grade)
        give_back()
        return told

    sent = exchange.relayed(dealt.groupBy("block").applyInArrow(send, LETTERS), "u4", "u2")
    return exchange.relayed(sent.groupBy("a", "b").applyInArrow(answer, LETTERS), "u4", "u1", back=True)


def known(table: pa.Table, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """The codes of a block's shared values, ascending, and the class of how many hold each."""
    _, bucket, rest, grade = opened(table, "u4", "u1")
    every = rest.astype(np.uint64) * np.uint64(buckets) + bucket.astype(np.uint64)
    order = np.argsort(every)
    return every[order], grade[order]


def within(sorted_codes: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Index of each wanted code, or -1."""
    if not len(sorted_codes):
        return np.full(len(wanted), -1)
    at = np.minimum(np.searchsorted(sorted_codes, wanted), len(sorted_codes) - 1)
    return np.where(sorted_codes[at] == wanted, at, -1)
