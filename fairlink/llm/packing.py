"""Packing of tokenised documents into training windows with the sum-of-squares rule.

Every task tokenises and packs the rows that it reads, in one pass and without a shuffle: a
window never mixes rows of two tasks, so a lost executor repeats its own rows only and makes
the same windows again. A document longer than a window is cut into whole windows and a rest;
rests are placed online. The state of a task is an array with the number of open windows at
each fill level and those windows' pieces. A new rest goes to the level that leaves the sum of
the squared counts of partly filled windows smallest, or opens a window. When the input ends, the open windows
stay as the rule filled them, the fullest first, and their gaps are closed with ids of the emptiest ones, which
alone are cut anew; so a task pads its last window only.

Null texts are empty texts; an empty text is its end mark alone. Repeated rows are packed each.
"""

from __future__ import annotations

import os
import re
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from fairlink.llm.common import RowBuffer, kept, slices

WINDOW = 2048
END_ID = 1
CACHED_WORDS = 400_000
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
_SCHEMA = pa.schema([(x.split()[0], pa.int64()) for x in PIECES.split(", ")])


class LevelPacker:
    """Online sum-of-squares packing of sizes below the capacity into windows."""

    def __init__(self, capacity: int):
        self.capacity = capacity
        self.counts = np.zeros(capacity + 1, np.int64)
        self.open: list[list[list]] = [[] for _ in range(capacity + 1)]

    def place(self, size: int, item) -> list | None:
        """Puts the item; the contents of the window that it filled, if it filled one."""
        top = self.capacity
        if size == top:
            return [item]
        counts = self.counts
        level, best = 0, 2 * counts[size] + 1
        used = np.flatnonzero(counts[1 : top - size + 1]) + 1
        if used.size:
            after = used + size
            change = 2 - 2 * counts[used] + 2 * counts[after]
            change[after == top] = 1 - 2 * counts[used[after == top]]
            k = int(np.argmin(change))
            if change[k] <= best:
                level = int(used[k])
        window = self.open[level].pop() if level else []
        if level:
            counts[level] -= 1
        window.append(item)
        if level + size == top:
            return window
        counts[level + size] += 1
        self.open[level + size].append(window)
        return None

    def drain(self) -> list[tuple[int, list]]:
        """The open windows with their fill, the fullest first; none is open after."""
        left = [(level, window) for level in range(self.capacity, 0, -1) for window in self.open[level]]
        self.open = [[] for _ in self.open]
        self.counts[:] = 0
        return left


def closed(windows: list[tuple[int, list[tuple]]], capacity: int) -> Iterator[list[tuple]]:
    """Full windows, and one that may not be, from open ones: the emptiest give their ids to the fullest."""
    last = len(windows) - 1
    giver: list[tuple] = []
    for at, (fill, pieces) in enumerate(windows):
        if at > last:
            break
        if at == last and giver:  # what is left of the giver
            pieces, fill = giver, sum(len(p[2]) // 4 for p in giver)
        room = capacity - fill
        while room and at < last:
            if not giver:
                giver = list(windows[last][1])
            doc, start, data, total = giver.pop()
            part = data[: 4 * room]
            pieces.append((doc, start, part, total))
            room -= len(part) // 4
            if len(part) < len(data):
                giver.append((doc, start + len(part) // 4, data[len(part) :], total))
            if not giver:
                last -= 1
        yield pieces


class WordIds:
    """Ids of texts as little-endian bytes, with a bounded cache of words in two generations.

    Words of plain Latin text are encoded once; any text with other characters goes through
    the tokenizer as a whole, so that its normalisation rules hold.
    """

    PLAIN = re.compile("[^\t\n\r\x20-\x7e\xa1-\xbf\xc0-\xff]")

    def __init__(self, path: str, words: int):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        vocabulary = self.tokenizer.get_vocab()
        self.ends = np.zeros(max(vocabulary.values()) + 1, bool)
        self.ends[[i for w, i in vocabulary.items() if w.endswith("</w>")]] = True
        # The vocabulary's own splitter, its classes written out for lower-case plain Latin text.
        letter, number = "a-z\xaa\xb5\xba\xdf-\xf6\xf8-\xff", "0-9\xb2\xb3\xb9\xbc-\xbe"
        self.find = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{letter}]+|[{number}]|[^\t\n\r {letter}{number}]+").findall
        self.cache: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        self.words = words

    def learn(self, words: Iterable[str]) -> None:
        """Puts words into the cache: from the one before, or encoded many at a time."""
        old = self.old.get
        fresh = []
        for w in words:
            ids = old(w)
            if ids is None:
                fresh.append(w)
            else:
                self.cache[w] = ids
        for at in range(0, len(fresh), 20_000):
            part = fresh[at : at + 20_000]
            ids = np.array(self.tokenizer.encode(" ".join(part), add_special_tokens=False).ids, "<u4")
            stops = np.flatnonzero(self.ends[ids]) + 1
            if len(stops) == len(part):
                data, cuts = ids.tobytes(), [0, *(stops * 4).tolist()]
                self.cache.update((w, data[a:b]) for w, a, b in zip(part, cuts[:-1], cuts[1:], strict=True))
            else:  # a word of the text is split otherwise beside a space
                for w in part:
                    self.cache[w] = np.array(self.tokenizer.encode(w, add_special_tokens=False).ids, "<u4").tobytes()

    def encode(self, texts: list[str]) -> list[bytes]:
        if len(self.cache) > self.words:
            self.old, self.cache = self.cache, {}
        get, out, holes = self.cache.get, [], []
        for text in texts:
            if self.PLAIN.search(text):
                out.append([np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()])
                continue
            words = self.find(text.lower())
            found = list(map(get, words))
            at = -1
            for _ in range(found.count(None)):
                at = found.index(None, at + 1)
                holes.append((found, at, words[at]))
            out.append(found)
        if holes:
            self.learn({w for _, _, w in holes})
            for found, at, w in holes:
                found[at] = self.cache[w]
        return [b"".join(found) for found in out]


def encoder(path: str, words: int) -> WordIds:
    """One encoder a worker process, kept from task to task."""
    return kept(("words", path, words), lambda: WordIds(path, words))


def pack_task(rows: Iterator[tuple[int, bytes]], first_id: int, window: int, end_id: int) -> Iterator[tuple]:
    """Piece rows (without the Arrow dress) for one task's documents, given as id bytes."""
    packer, sequence = LevelPacker(window), first_id
    end = np.array([end_id], "<u4").tobytes()

    def put(pieces: list[tuple]) -> Iterator[tuple]:
        nonlocal sequence
        offset = 0
        for doc, start, data, total in pieces:
            n = len(data) // 4
            yield doc, start, n, zlib.crc32(data), total, sequence, offset
            offset += n
        sequence += 1

    for doc, ids in rows:
        data = ids + end
        total = len(data) // 4
        for start in range(0, total, window):
            part = data[4 * start : 4 * (start + window)]
            done = packer.place(len(part) // 4, (doc, start, part, total))
            if done:
                yield from put(done)
    for pieces in closed(packer.drain(), window):
        yield from put(pieces)


def pack(docs: DataFrame, vocabulary: str, window: int = WINDOW, end_id: int = END_ID, words: int = CACHED_WORDS) -> DataFrame:
    """One row per piece: where its ids lie in the document and in which window at which offset.

    words: how many words a worker keeps the ids of, in each of two generations; rows do not depend on it.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = encoder(vocabulary, words)
        out = RowBuffer(_SCHEMA)

        def rows() -> Iterator[tuple[int, bytes]]:
            for keys, texts in slices(batches, "doc_id", "text"):
                yield from zip(keys, ids.encode([t or "" for t in texts]), strict=True)

        for row in pack_task(rows(), TaskContext.get().partitionId() << 40, window, end_id):
            out.add(row)
            if out.full():
                yield out.take()
        yield out.take()

    return docs.select("doc_id", "text").mapInArrow(run, PIECES)
