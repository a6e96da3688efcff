"""Byte-level BPE by recursive SQL inside each task.

A task splits its texts into words and puts the distinct ones as token-position rows into an in-process DuckDB
table: a row a byte, or one row for a word that the vocabulary holds whole, as the ranks demand. A recursive query
contracts them: each round joins neighbouring tokens with the merge table, takes each word's leftmost pair of
least rank, and hands on the words that changed, until none does. Ordered aggregation then gives each word its ids
and, through the vocabulary, its decoded bytes; a text's digest strings are its words' in order. Results of words are
kept in a bounded cache between the slices and tasks of a worker, so a frequent word is contracted once.

Words above SHORT bytes go to a second query, which keeps the present tokens only (a keyed recursion) and makes many
contractions a round. A pair may go at once when no pair within reach, the longest token's number of bytes, is less,
or as little and further left: whatever could take one of its two tokens before would have to be built from a lesser
pair within reach. Equal pairs within reach go in one round where the token that they make forms no pair of lesser rank with
what is beside it; of overlapping ones every second. So a word's rounds do not grow with its length, and memory is that
of its tokens; DuckDB spills beyond its limit to a folder of the worker that ends with it.

Memory is bounded by the cache, the slice, the longest word and DuckDB's own limit, and no row leaves its task.

Null texts count as empty; repeated rows and ties need no rule, as rows do not meet.
"""

from __future__ import annotations

import base64
import hashlib
import re
import tempfile
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from fairlink.llm.common import RowBuffer, kept, slices

ENCODED = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
_SCHEMA = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])

#: seed: w word, p position, t token; merges: ab the pair as one key, r the rank, which is also
#: the id of the joined token; vocabulary: t, hex.
_DECODED = """
SELECT w, string_agg(settled.t::VARCHAR, ',' ORDER BY p) AS ids, unhex(string_agg(vocabulary.hex, '' ORDER BY p)) AS code
FROM settled JOIN vocabulary ON vocabulary.t = settled.t
GROUP BY w
"""
CONTRACT = f"""
WITH RECURSIVE walk(w, p, t, q, step) AS (
    SELECT w, p, t, lead(t) OVER (PARTITION BY w ORDER BY p), 0 FROM seed
    UNION ALL (
        WITH best AS (
            SELECT walk.w, min(merges.r::BIGINT * 4294967296 + walk.p) AS pick
            FROM walk JOIN merges ON merges.ab = walk.t::BIGINT * 65536 + walk.q
            GROUP BY walk.w
        ), put AS (
            SELECT walk.w, walk.p, walk.step,
                CASE WHEN walk.p = (best.pick & 4294967295) THEN (best.pick >> 32)::INTEGER ELSE walk.t END AS t,
                lag(walk.p) OVER (PARTITION BY walk.w ORDER BY walk.p) IS NOT DISTINCT FROM (best.pick & 4294967295) AS taken
            FROM walk JOIN best ON walk.w = best.w
        )
        SELECT w, p, t, lead(t) OVER (PARTITION BY w ORDER BY p), step + 1 FROM put WHERE NOT taken
    )
), settled AS (
    SELECT walk.w, walk.p, walk.t FROM walk JOIN (SELECT w, max(step) AS last FROM walk GROUP BY w) AS ends ON ends.w = walk.w AND ends.last = walk.step
)
{_DECODED}"""
#: For long words. t is -1 where a byte's token went into the one before; `least`: no pair within reach is less;
#: `calm`: the token that a pair makes forms no pair of lesser rank with its neighbours; run: consecutive pairs of one rank.
CONTRACT_LONG = f"""
WITH RECURSIVE walk(w, p, t) USING KEY (w, p) AS (
    SELECT w, p, t FROM seed
    UNION (
        WITH paired AS (
            SELECT w, p, t, lag(t) OVER o AS before, lead(t) OVER o AS q, lead(t, 2) OVER o AS after
            FROM recurring.walk WHERE t >= 0 AND w IN (SELECT w FROM walk) WINDOW o AS (PARTITION BY w ORDER BY p)
        ), ranked AS (
            SELECT paired.*, merges.r::BIGINT AS r FROM paired LEFT JOIN merges ON merges.ab = t::BIGINT * 65536 + q
        ), seen AS (
            SELECT *, r <= min(r) OVER (PARTITION BY w ORDER BY p ROWS BETWEEN $REACH PRECEDING AND $REACH FOLLOWING) AS least,
                lag(r) OVER (PARTITION BY w ORDER BY p) IS DISTINCT FROM r AS fresh
            FROM ranked
        ), runs AS (
            SELECT * EXCLUDE (fresh), sum(fresh::INTEGER) OVER (PARTITION BY w ORDER BY p ROWS UNBOUNDED PRECEDING) AS run FROM seen
        ), known AS (
            SELECT runs.*, coalesce(x.r > runs.r, true) AND coalesce(y.r > runs.r, true) AND coalesce(z.r > runs.r, true) AS calm
            FROM runs LEFT JOIN merges x ON least AND x.ab = before::BIGINT * 65536 + runs.r
                LEFT JOIN merges y ON least AND y.ab = runs.r * 65536 + after LEFT JOIN merges z ON least AND z.ab = runs.r * 65536 + runs.r
        ), judged AS (
            SELECT w, p, t, r, run, bool_and(least) OVER c AS least, bool_and(calm) OVER c AS calm, row_number() OVER (PARTITION BY w, run ORDER BY p) - 1 AS place
            FROM known WINDOW c AS (PARTITION BY w, run)
        ), bound AS (
            SELECT *, min(2 * r + (least AND calm)::INTEGER) OVER (PARTITION BY w ORDER BY p ROWS BETWEEN $REACH PRECEDING AND 1 PRECEDING) AS lower FROM judged
        ), chosen AS (
            SELECT w, p, t, r, r IS NOT NULL AND least AND place % 2 = 0 AND (place = 0 OR calm)
                AND first_value(coalesce(lower > 2 * r, true)) OVER (PARTITION BY w, run ORDER BY p) AS joins
            FROM bound
        ), put AS (
            SELECT w, p, t, r, joins, coalesce(lag(joins) OVER (PARTITION BY w ORDER BY p), false) AS taken FROM chosen
        )
        SELECT w, p, CASE WHEN joins THEN r::INTEGER ELSE -1 END FROM put WHERE joins OR taken
    )
), settled AS (
    SELECT w, p, t FROM walk WHERE t >= 0
)
{_DECODED}"""
#: Bytes of a word for the first query, whose rows are kept from all rounds, and the sum of their squares at a time.
SHORT, SQUARES = 64, 6_000_000
#: Bytes of the long words that one query takes, but for a last one.
LONG_BYTES = 100_000
CACHED_BYTES = 32_000_000


#: The public splitting pattern, and what it comes to for texts of plain Latin characters.
GENERAL = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
_LETTER, _NUMBER = "A-Za-z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-\xff", "0-9\xb2\xb3\xb9\xbc-\xbe"
LATIN = f"'s|'t|'re|'ve|'m|'ll|'d| ?[{_LETTER}]+| ?[{_NUMBER}]+| ?[^\t\n\r {_LETTER}{_NUMBER}]+|[\t\n\r ]+(?![^\t\n\r ])|[\t\n\r ]+"
PLAIN = re.compile("[^\t\n\r\x20-\x7e\xa1-\xff]")


class RankCoder:
    """Contracts words by the ranks of a vocabulary file."""

    def __init__(self, path: str, pattern: str, words: int = 800_000, memory: str = "300MB"):
        import duckdb
        import regex

        with open(path, "rb") as lines:
            self.ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        left, right, rank = [], [], []
        for token, r in self.ranks.items():
            for cut in range(1, len(token)):
                a, b = self.ranks.get(token[:cut]), self.ranks.get(token[cut:])
                if a is not None and b is not None:
                    left.append(a), right.append(b), rank.append(r)
        self.bytes = np.array([self.ranks[bytes([i])] for i in range(256)], np.int32)
        self.split = self.split_plain = regex.compile(pattern).findall
        if pattern == GENERAL:
            self.split_plain = re.compile(LATIN).findall
        self.spill = tempfile.TemporaryDirectory(prefix="spill-")
        self.sql = duckdb.connect(config={"threads": 1, "memory_limit": memory, "temp_directory": self.spill.name, "preserve_insertion_order": False})
        pairs = pa.table({"ab": np.array(left, np.int64) * 65536 + np.array(right, np.int64), "r": np.array(rank, np.int32)})  # noqa: F841
        names = pa.table({"t": pa.array(self.ranks.values(), pa.int32()), "hex": [b.hex() for b in self.ranks]})  # noqa: F841
        self.sql.execute("CREATE TABLE merges AS SELECT * FROM pairs")
        self.sql.execute("CREATE TABLE vocabulary AS SELECT * FROM names")
        self.ids: dict[str, str] = {}
        self.data: dict[str, bytes] = {}
        self.words, self.held = words, 0
        self.long = CONTRACT_LONG.replace("$REACH", str(max(map(len, self.ranks))))

    def contract(self, words: list[bytes], long: bool = False) -> list[tuple[str, bytes]]:
        """Ids joined by commas, and decoded bytes of each word."""
        rows = [np.array([r], np.int32) if (r := self.ranks.get(w)) is not None else self.bytes[np.frombuffer(w, np.uint8)] for w in words]
        sizes = np.array([len(x) for x in rows])
        seed = pa.table(  # noqa: F841
            {
                "w": np.repeat(np.arange(len(words), dtype=np.int32), sizes),
                "p": (np.arange(int(sizes.sum())) - np.repeat(np.cumsum(sizes) - sizes, sizes)).astype(np.int32),
                "t": np.concatenate(rows),
            }
        )
        found = self.sql.sql(self.long if long else CONTRACT).to_arrow_table()
        out: list = [None] * len(words)
        for w, ids, code in zip(*(found.column(c).to_pylist() for c in ("w", "ids", "code")), strict=True):
            out[w] = ids, code
        return out

    def learn(self, fresh: list[str]) -> None:
        part, squares = [], 0
        long, held = [], 0

        def settle(words: list[str], many: bool = False) -> None:
            for word, (ids, data) in zip(words, self.contract([w.encode() for w in words], many), strict=True):
                self.ids[word], self.data[word] = ids, data
                self.held += len(data)

        for word in fresh:
            size = len(word.encode())
            if size > SHORT:
                long.append(word)
                held += size
                if held >= LONG_BYTES:
                    settle(long, True)
                    long, held = [], 0
                continue
            part.append(word)
            squares += size * size
            if squares >= SQUARES:
                settle(part)
                part, squares = [], 0
        if part:
            settle(part)
        if long:
            settle(long, True)

    def encode(self, texts: list[str]) -> list[tuple[int, str, bytes]]:
        """Number of ids, ids joined by commas, and decoded bytes of each text."""
        split = [(self.split_plain if not PLAIN.search(t) else self.split)(t) for t in texts]
        seen = set(chain.from_iterable(split))
        fresh = seen.difference(self.ids)
        if len(self.ids) + len(fresh) > self.words or self.held > CACHED_BYTES:
            self.ids.clear(), self.data.clear()
            fresh, self.held = seen, 0
        if fresh:
            self.learn(list(fresh))
        out = []
        for words in split:
            joined = ",".join(map(self.ids.__getitem__, words))
            out.append((joined.count(",") + 1 if words else 0, joined, b"".join(map(self.data.__getitem__, words))))
        return out


def coder(path: str, pattern: str) -> RankCoder:
    """One coder a worker process, kept from task to task."""
    return kept(("ranks", path, pattern), lambda: RankCoder(path, pattern))


def encode_decode(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """Per document the number of ids, the digest of the ids and that of the decoded bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code, out = coder(path, pattern), RowBuffer(_SCHEMA)
        pending_keys: list = []
        pending: list = []

        def flush() -> None:
            for key, (n, ids, data) in zip(pending_keys, code.encode(pending), strict=True):
                out.add((key, n, hashlib.sha256(ids.encode()).hexdigest(), hashlib.sha256(data).hexdigest()))
            pending_keys.clear(), pending.clear()

        size = 0
        for keys, texts in slices(batches, "doc_id", "text"):
            pending_keys.extend(keys), pending.extend(t or "" for t in texts)
            size += sum(map(len, pending[-len(keys) :]))
            if size >= 8_000_000:  # so many characters share one recursive query
                flush()
                size = 0
            if out.full():
                yield out.take()
        flush()
        yield out.take()

    return docs.select("doc_id", "text").mapInArrow(run, ENCODED)
