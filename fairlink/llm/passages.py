"""Removal of repeated passages by threshold-bounded interval expansion on a suffix order.

Every window of LENGTH bytes has an anchor: the leftmost of its inner runs of K bytes with the
least hash, which depends on the window's bytes alone. Consecutive windows with one anchor make
a segment. Anchors that one document alone holds are dropped by the exchange of `blocks`; the
other segments go to the bucket that their anchor names, once per block and content, with the
smallest doc_id that holds them. So equal windows meet in one bucket, and a passage that a
third of all rows share arrives there once per block.

A bucket then finds which windows are equal. Its distinct segments form one text; the state is the
list of intervals of its suffix order, each the set of places where one string occurs.
Breadth first, every interval is extended backwards: the two symbols that precede each place are
read in suffix order (the Burrows-Wheeler transform over pairs of bytes), and a stable radix sort by them is the step from
an interval to those of all its extensions. So common prefixes come by increasing length; an
interval that holds one place only is dropped, and expansion stops at LENGTH. The smallest doc_id in
a final interval is the first holder of its window; blocks get it back per segment and mark the
bytes under windows that an earlier document holds.

Null texts are empty. Texts shorter than LENGTH bytes are kept whole. Rows with equal doc_id never
remove each other's bytes; rows without doc_id neither remove nor lose any.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from fairlink.llm.blocks import LETTERS, Exchange, chunks, code, deal, known, opened, shared, within
from fairlink.llm.common import give_back
from fairlink.llm.fingerprints import _least

LENGTH = 50
K = 20
SPREAD = LENGTH - K + 1  # places of an anchor in a window
WIDTH = 2 * LENGTH - K  # bytes of a segment at most
#: Types of what blocks send (windows, smallest doc_id, whether more than one, bytes) and are told (name, first window, windows, holder).
SEGMENTS, HOLDERS = ("u1", "i8", "u1", f"{WIDTH}u1"), ("u8", "u1", "u1", "i8")
_P = np.uint64(0x9E3779B97F4A7C15)


def _mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(31))
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(32))


class Segments:
    """The segments of some byte strings laid end to end."""

    def __init__(self, texts: list[bytes]):
        self.flat = np.frombuffer(b"".join(texts), np.uint8)
        self.sizes = np.array([len(t) for t in texts], np.int64)
        self.ends = np.cumsum(self.sizes)
        self.starts = self.ends - self.sizes
        n = len(self.flat)
        if n < LENGTH:
            self.first = self.windows = self.doc = np.zeros(0, np.int64)
            self.anchor = np.zeros(0, np.uint64)
            return
        # Hash of K = 16 + 4 bytes at each place, by doubling.
        power, width, runs = 0x01000193, 1, {1: self.flat.astype(np.uint32)}
        while width < 16:
            x = runs[width]
            runs[2 * width] = x[:-width] * np.uint32(power) + x[width:]
            power, width = power * power & 0xFFFFFFFF, 2 * width
        h = runs[16][: n - K + 1] * np.uint32(0x01000193) + runs[4][16 : n - K + 17]
        h ^= h >> np.uint32(15)
        h *= np.uint32(0x85EBCA6B)
        h ^= h >> np.uint32(13)
        h *= np.uint32(0xC2B2AE35)
        key = (h.astype(np.uint64) << np.uint64(32)) | np.arange(len(h), dtype=np.uint64)
        place = (_least(key, SPREAD) & np.uint64(0xFFFFFFFF)).astype(np.int64)
        change = np.zeros(n + 1, np.int32)
        long = self.sizes >= LENGTH
        np.add.at(change, self.starts[long], 1)
        np.add.at(change, self.ends[long] - LENGTH + 1, -1)
        at = np.flatnonzero(np.cumsum(change[: len(place)]) > 0)
        place = place[at]
        begin = np.flatnonzero(np.r_[True, (place[1:] != place[:-1]) | (at[1:] != at[:-1] + 1)]) if len(at) else np.zeros(0, np.int64)
        self.first = at[begin]
        self.windows = np.diff(np.r_[begin, len(at)])
        self.doc = np.searchsorted(self.ends, self.first, side="right")
        value = np.zeros(len(begin), np.uint64)
        for i in range(K):
            value = value * _P + self.flat[place[begin] + i]
        self.anchor = _mix(value)

    def contents(self, chosen: np.ndarray) -> np.ndarray:
        """The bytes of chosen segments, a row each, filled up with zeros."""
        first, size = self.first[chosen], self.windows[chosen] + LENGTH - 1
        padded = np.r_[self.flat, np.zeros(WIDTH, np.uint8)]
        out = np.lib.stride_tricks.sliding_window_view(padded, WIDTH)[first]
        out[np.arange(WIDTH) >= size[:, None]] = 0
        return out


def names(contents: np.ndarray, windows: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each segment."""
    words = np.ascontiguousarray(contents).view(np.uint64)
    value = windows.astype(np.uint64)
    for i in range(words.shape[1]):
        value = _mix(value * _P + words[:, i])
    return value


def anchors(texts: list[str]) -> list[np.ndarray]:
    """The distinct anchors of each text."""
    s = Segments([t.encode() for t in texts])
    cuts = np.searchsorted(s.doc, np.arange(len(texts) + 1))
    return [np.unique(s.anchor[a:b]) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]


def equal_windows(contents: np.ndarray, windows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Window numbers in order of their final intervals, and where intervals start.

    Windows are numbered segment by segment. Only windows whose bytes occur twice are listed.
    """
    flat = np.ascontiguousarray(contents).ravel()
    pair = np.empty(len(flat), np.uint16)
    pair[:-1] = (flat[:-1].astype(np.uint16) << np.uint16(8)) | flat[1:]
    pair[-1:] = 0
    before = np.cumsum(windows) - windows
    number = np.arange(int(windows.sum()))
    owner = np.repeat(np.arange(len(windows)), windows)
    place = (owner * WIDTH + number - before[owner] + LENGTH).astype(np.int64)
    interval = np.zeros(len(place), np.int32)
    for _ in range(LENGTH // 2):
        place -= 2
        symbol = pair[place]
        order = np.argsort(symbol, kind="stable")
        symbol, interval, place = symbol[order], interval[order], place[order]
        new = np.empty(len(place) + 1, bool)
        new[:1] = new[-1:] = True
        new[1:-1] = (symbol[1:] != symbol[:-1]) | (interval[1:] != interval[:-1])
        alive = ~(new[:-1] & new[1:])
        place, interval = place[alive], np.cumsum(new[:-1])[alive].astype(np.int32)
        if not len(place):
            break
    row = place // WIDTH
    starts = np.flatnonzero(np.r_[True, interval[1:] != interval[:-1]]) if len(place) else np.zeros(0, np.int64)
    return before[row] + place - row * WIDTH, starts


def _spread(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The numbers start, start + 1, ... of every range, in order."""
    total = int(counts.sum())
    return np.repeat(starts - (np.cumsum(counts) - counts), counts) + np.arange(total)


def _meet(table: pa.Table, exchange: Exchange) -> pa.Table:
    """For each block the first holders of its segments' windows, as runs: segment's name, first window, windows, holder."""
    block, bucket, windows, doc, several, contents = opened(table, *SEGMENTS)
    windows = windows.astype(np.int64)
    name = names(contents, windows)
    every, first, inverse = np.unique(name, return_index=True, return_inverse=True)
    if not (contents == contents[first[inverse]]).all() or (windows != windows[first[inverse]]).any():
        raise RuntimeError("two segments have one 64-bit name")
    holder = np.full(len(every), np.iinfo(np.int64).max)
    np.minimum.at(holder, inverse, doc)
    count = windows[first]
    earliest = np.repeat(holder, count)
    listed, starts = equal_windows(contents[first], count)
    if len(listed):
        sizes = np.diff(np.r_[starts, len(listed)])
        earliest[listed] = np.repeat(np.minimum.reduceat(earliest[listed], starts), sizes)
    # Runs of windows with one first holder.
    begin = np.cumsum(count) - count
    change = np.ones(len(earliest), bool)
    change[1:] = earliest[1:] != earliest[:-1]
    change[begin] = True
    run = np.flatnonzero(change)
    length = np.diff(np.r_[run, len(earliest)])
    runs_from = np.searchsorted(run, begin)
    runs = np.diff(np.r_[runs_from, len(run)])
    least = np.minimum.reduceat(earliest, begin)
    told = np.flatnonzero((least[inverse] < doc) | (several > 0))
    own = inverse[told]
    picks = _spread(runs_from[own], runs[own])
    each = lambda values: np.repeat(values, runs[own])
    into = run[picks] - each(begin[own])
    return exchange.letters(exchange.steps - 1, each(block[told]), each(bucket[told]), each(every[own]), into.astype(np.uint8), length[picks].astype(np.uint8), earliest[run[picks]])


def without_repeats(docs: DataFrame, carry: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept (bytes) and the carried columns of every row."""
    dealt, exchange = deal(docs, carry)
    buckets = exchange.buckets

    def send(key: tuple, rows: pa.Table, told: pa.Table) -> pa.Table:
        codes, _ = known(told, buckets)
        found = []
        for texts, keys in chunks(rows, "doc_id"):
            own = np.array([k is not None for k in keys])
            ids = np.array([k or 0 for k in keys], np.int64)
            s = Segments([t.encode() for t in texts])
            if not len(s.first):
                continue
            chosen = np.flatnonzero((within(codes, code(s.anchor, buckets)) >= 0) & own[s.doc])
            contents = s.contents(chosen)
            found.append((s.windows[chosen], ids[s.doc[chosen]], contents, names(contents, s.windows[chosen]), (s.anchor[chosen] % np.uint64(buckets)).astype(np.int32)))
        none = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros((0, WIDTH), np.uint8), np.zeros(0, np.uint64), np.zeros(0, np.int64))]
        windows, ids, contents, name, bucket = (np.concatenate(x) for x in zip(*(found or none), strict=True))
        order = np.lexsort((ids, name))
        ids, name = ids[order], name[order]
        starts = np.flatnonzero(np.r_[True, name[1:] != name[:-1]]) if len(name) else np.zeros(0, np.int64)
        last = (np.r_[starts[1:], len(name)] - 1)[: len(starts)]
        several = (ids[last] != ids[starts]).astype(np.uint8)
        pick = order[starts]
        return exchange.letters(1, np.full(len(pick), key[0].as_py()), bucket[pick], windows[pick].astype(np.uint8), ids[starts], several, contents[pick])

    def meet(key: tuple, table: pa.Table) -> pa.Table:
        told = _meet(table, exchange)
        give_back()
        return told

    kept = T.StructType(
        [T.StructField("doc_id", T.LongType()), *(T.StructField(n, T.LongType()) for n in ("n_bytes", "n_removed", "n_spans")), T.StructField("kept", T.BinaryType()), *(docs.schema[c] for c in carry)]
    )

    def remove(key: tuple, rows: pa.Table, told: pa.Table) -> pa.Table:
        _, _, name, into, length, earliest = opened(told, *HOLDERS)
        order = np.lexsort((into, name))
        name, into, length, earliest = name[order], into[order].astype(np.int64), length[order].astype(np.int64), earliest[order]
        begin = np.flatnonzero(np.r_[True, name[1:] != name[:-1]]) if len(name) else np.zeros(0, np.int64)
        ranked, runs = name[begin], np.diff(np.r_[begin, len(name)])[: len(begin)]
        done: dict[str, list] = {f.name: [] for f in kept}
        for texts, keys, *more in chunks(rows, "doc_id", *carry):
            data = [t.encode() for t in texts]
            s = Segments(data)
            cover = np.zeros(len(s.flat) + 1, np.int32)
            if len(ranked) and len(s.first):
                every = np.arange(len(s.first))
                hit = within(ranked, names(s.contents(every), s.windows))
                mine = np.flatnonzero(hit >= 0)
                entry = hit[mine]
                picks = _spread(begin[entry], runs[entry])
                owner = np.repeat(mine, runs[entry])
                ids = np.array([np.iinfo(np.int64).min if k is None else k for k in keys], np.int64)
                earlier = earliest[picks] < ids[s.doc[owner]]
                first = s.first[owner][earlier] + into[picks][earlier]
                np.add.at(cover, first, 1)
                np.add.at(cover, first + length[picks][earlier] + LENGTH - 1, -1)
            gone = np.cumsum(cover[:-1]) > 0
            for i, text in enumerate(data):
                a, b = s.starts[i], s.ends[i]
                mask = gone[a:b]
                removed = int(np.count_nonzero(mask))
                done["doc_id"].append(keys[i])
                done["n_bytes"].append(len(text))
                done["n_removed"].append(removed)
                done["n_spans"].append(int(np.count_nonzero(mask[1:] & ~mask[:-1])) + int(mask[0]) if removed else 0)
                done["kept"].append(s.flat[a:b][~mask].tobytes() if removed else text)
            for name_, values in zip(carry, more, strict=True):
                done[name_].extend(values)
        from pyspark.sql.pandas.types import to_arrow_schema

        give_back()
        return pa.table(done, schema=to_arrow_schema(kept))

    by = dealt.groupBy("block")
    asked = by.cogroup(shared(dealt, anchors, exchange).groupBy("a")).applyInArrow(send, LETTERS)
    met = exchange.relayed(asked, *SEGMENTS).groupBy("a", "b").applyInArrow(meet, LETTERS)
    return by.cogroup(exchange.relayed(met, *HOLDERS, back=True).groupBy("a")).applyInArrow(remove, kept)


def repeats(docs: DataFrame) -> DataFrame:
    """The digest of what is left of every document."""
    return without_repeats(docs).select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


#: The same in DuckDB: every window of every text, its first holder, and what lies under later ones.
ORACLE = f"""
WITH bytes AS (
    SELECT doc_id, hex(encode(coalesce(text, ''))) AS h, strlen(coalesce(text, '')) AS n FROM documents
), windows AS (
    SELECT doc_id, i, md5_number(substr(h, 2 * i + 1, {2 * LENGTH})) AS g FROM bytes, unnest(range(0, n - {LENGTH - 1})) u(i)
), firsts AS (
    SELECT g, min(doc_id) AS doc FROM windows GROUP BY g HAVING min(doc_id) < max(doc_id)
), later AS (
    SELECT doc_id, i FROM windows JOIN firsts USING (g) WHERE doc < doc_id
), marked AS (
    SELECT doc_id, i, i + {LENGTH} AS stop, CASE WHEN i <= lag(i + {LENGTH}) OVER (PARTITION BY doc_id ORDER BY i) THEN 0 ELSE 1 END AS fresh FROM later
), spans AS (
    SELECT doc_id, min(i) AS a, max(stop) AS b FROM (SELECT *, sum(fresh) OVER (PARTITION BY doc_id ORDER BY i) AS span FROM marked) GROUP BY doc_id, span
), pieces AS (
    SELECT doc_id, a, b, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a), 0) AS since FROM spans
), gone AS (
    SELECT doc_id, sum(b - a)::BIGINT AS removed, count(*) AS spans, string_agg(substr(h, 2 * since + 1, 2 * (a - since)), '' ORDER BY a) AS head, max(b) AS tail
    FROM pieces JOIN bytes USING (doc_id) GROUP BY doc_id
)
SELECT doc_id, n::BIGINT AS n_bytes, coalesce(removed, 0)::BIGINT AS n_removed, coalesce(spans, 0)::BIGINT AS n_spans,
    sha256(unhex(coalesce(head, '') || substr(h, 2 * coalesce(tail, 0) + 1))) AS kept_sha256
FROM bytes LEFT JOIN gone USING (doc_id)
"""
