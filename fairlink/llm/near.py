"""Exact n-gram Jaccard join by T-occurrence search, and its connected classes.

A text's set holds the hashes of its runs of five words. The exchange of `blocks` tells every
block which of its hashes other documents hold too, and by how many (as a class). Ordered from
rare to frequent, the first n - ceil(0.8 n) + 1 hashes of a set must hold one in common with any
partner; hashes that nobody else holds come first and meet nobody, so few sets have entries at
all. Those candidates' sets are written out once, and whatever follows reads them alone.

Documents that share an entry are compared, but not all with all. First each entry's most central
document (that with the smallest share of hashes of its own) is the query for the entry's other
documents; what links is joined to classes. Then pairs of different classes that share an
entry and could be alike by size are compared, so no link between classes is lost: entries of at most LIGHT documents list
their pairs, so many a document at most; the documents of a frequent entry are cut by a hash into parts of about 2 * GROUP,
and every two parts meet in a task of their own, in which each document of one is a query to the inverted lists of the other.

A query is answered by DivideSkip over groups of at most GROUP candidates: the inverted lists of the
query's hashes over the group are divided, the longest are set aside, the short ones are merged on
a heap, and what occurs there often enough is probed in the long lists by binary search. What
reaches the required overlap is checked with whole sizes. Groups are cut by a hash, so a query
with very many candidates is spread over tasks.

Before sets travel, pairs are held against parities: a set of n hashes has as many bits as the power of two from n on, and
each says whether an odd number of its hashes falls there. Two parities differ in no more bits than the sets in hashes, so
a pair that differs in more bits than alike sets may is none; no link is lost, and few sets of other pairs are sent.

Words are runs without ASCII white space with A-Z in lower case. A text with fewer words than
five is one shingle, its words in sequence; without words or with null text the set is empty and
links with nothing. Rows of one doc_id are one vertex; rows without doc_id keep a null class.
"""

from __future__ import annotations

import heapq
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fairlink.llm.blocks import chunks, code, deal, known, shared, within
from fairlink.llm.common import durable, give_back
from fairlink.llm.passages import _mix

WORDS = 5
PERCENT = 80
GROUP = 256
LIGHT = 64
SALTS = 64
FEW = 100_000
_P = np.uint64(0x9E3779B97F4A7C15)
_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 2**64))


def shingle_sets(texts: list[str], words: int = WORDS) -> list[np.ndarray]:
    """The distinct shingle hashes of each text, ascending."""
    parts = [t.encode() + b"\n" for t in texts]
    raw = np.frombuffer(b"".join(parts), np.uint8)
    lower = np.where((raw >= 65) & (raw <= 90), raw | 32, raw)
    n = len(raw)
    powers, inverses = np.full(n + 1, _P), np.full(n + 1, _INVERSE)
    powers[0] = inverses[0] = 1
    np.cumprod(powers, out=powers), np.cumprod(inverses, out=inverses)
    sums = np.zeros(n + 1, np.uint64)
    np.cumsum((lower.astype(np.uint64) + np.uint64(1)) * inverses[:n], out=sums[1:])
    space = (raw == 32) | ((raw >= 9) & (raw <= 13))
    step = np.diff(np.r_[True, space].astype(np.int8))
    first, after = np.flatnonzero(step == -1), np.flatnonzero(step == 1)
    word = _mix((sums[after] - sums[first]) * powers[first])
    ends = np.cumsum([len(p) for p in parts])
    lo, hi = np.searchsorted(first, np.r_[0, ends[:-1]]), np.searchsorted(first, ends)

    def runs(of: np.ndarray, size: int) -> np.ndarray:
        value = np.full(max(0, len(of) - size + 1), np.uint64(size))
        for i in range(size):
            value = _mix(value * _P + of[i : i + len(value)])
        return value

    every = runs(word, words)
    return [np.unique(every[a : b - words + 1]) if b - a >= words else runs(word[a:b], int(b - a)) if b > a else np.zeros(0, np.uint64) for a, b in zip(lo, hi, strict=True)]


def entries(own: np.ndarray, codes: np.ndarray, grades: np.ndarray, buckets: int, percent: int = PERCENT) -> tuple[np.ndarray, np.ndarray, int]:
    """The set's prefix hashes that others hold too, their places in its order, and how many of its hashes nobody else holds."""
    n = len(own)
    if not n:
        return own, own, 0
    at = within(codes, code(own, buckets))
    grade = np.where(at >= 0, grades[at].astype(np.int64), np.int64(-1)) if len(grades) else np.full(n, -1)
    prefix = np.lexsort((own, grade))[: n - math.ceil(percent * n / 100) + 1]
    place = np.flatnonzero(grade[prefix] >= 0)
    return own[prefix[place]], place, int(np.count_nonzero(at < 0))


def divide_skip(lists: list[np.ndarray], least: int, mu: float = 0.0085) -> list[tuple[int, int]]:
    """(member, occurrences) for members in at least `least` of the sorted lists, least >= 1."""
    lists = sorted((x for x in lists if len(x)), key=len)
    if len(lists) < least:
        return []
    longest = len(lists[-1])
    aside = min(least - 1, int(least / (mu * math.log2(longest) + 1)) if longest > 1 else least - 1)
    short, long = lists[: len(lists) - aside], lists[len(lists) - aside :]
    found, seen, last = [], 0, None
    for member in heapq.merge(*(x.tolist() for x in short)):
        if member == last:
            seen += 1
            continue
        if last is not None and seen >= least - aside:
            found.append((last, seen))
        last, seen = member, 1
    if last is not None and seen >= least - aside:
        found.append((last, seen))
    if not found:
        return []
    members = np.array([m for m, _ in found])
    total = np.array([s for _, s in found])
    for x in long:
        at = np.minimum(np.searchsorted(x, members), len(x) - 1)
        total += x[at] == members
    return [(int(m), int(t)) for m, t in zip(members, total, strict=True) if t >= least]


def required(a: int, b: int, percent: int = PERCENT) -> int:
    """The least overlap of sets of a and b elements with 100 * overlap >= percent * union."""
    return -(-percent * (a + b) // (100 + percent))


def alike(query: np.ndarray, sets: list[np.ndarray], percent: int = PERCENT) -> list[int]:
    """Which of the sets have the required overlap with the query."""
    sizes = [len(s) for s in sets]
    fit = [i for i, n in enumerate(sizes) if n and 100 * min(n, len(query)) >= percent * max(n, len(query))]
    if not fit:
        return []
    need = {i: required(len(query), sizes[i], percent) for i in fit}
    hash_, member = np.concatenate([sets[i] for i in fit]), np.repeat(fit, [sizes[i] for i in fit])
    at = within(query, hash_)
    at, member = at[at >= 0], member[at >= 0]
    order = np.lexsort((member, at))
    at, member = at[order], member[order]
    cuts = np.flatnonzero(np.r_[True, at[1:] != at[:-1]]) if len(at) else []
    lists = np.split(member, cuts[1:]) if len(at) else []
    return [i for i, n in divide_skip(lists, min(need.values())) if n >= need[i]]


def parities(own: np.ndarray) -> np.ndarray:
    """Words of 64 bits; bit i says whether an odd number of hashes is i modulo the number of bits, a power of two from len(own) on."""
    size = 64
    while size < len(own):
        size *= 2
    odd = np.bincount((own & np.uint64(size - 1)).astype(np.int64), minlength=size) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view(np.int64)


def differing(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """In how many parities one row differs from each of many; the longer are folded to as many words as the shorter have."""
    sides = []
    for words in (a, b):
        while words.shape[-1] > min(a.shape[-1], b.shape[-1]):
            half = words.shape[-1] // 2
            words = words[..., :half] ^ words[..., half:]
        sides.append(words)
    # Of a negative number bitwise_count counts the bits of its absolute value.
    return np.bitwise_count((sides[0] ^ sides[1]).view(np.uint64)).sum(-1, dtype=np.int64)


def _at_odds(a: str, b: str, n: str, m: str) -> Column:
    """Whether sets of n and m hashes differ in more parities than alike sets may. Alike sizes' parities differ by a factor of two at most."""
    size = F.least(F.size(a), F.size(b))
    xor = lambda x, y: x.bitwiseXOR(y)
    half = lambda c: F.when(F.size(c) > size, F.zip_with(F.slice(c, F.lit(1), size), F.slice(c, size + 1, size), xor)).otherwise(F.col(c))
    differ = F.aggregate(F.zip_with(half(a), half(b), xor), F.lit(0), lambda total, x: total + F.bit_count(x).cast("int"))
    far = F.expr(f"100 * least({n}, {m}) < {PERCENT} * greatest({n}, {m})")
    return far | (differ > F.expr(f"({n} + {m}) - 2 * (({PERCENT} * ({n} + {m}) + {99 + PERCENT}) div {100 + PERCENT})"))


def plausible(pairs: DataFrame, marks: DataFrame) -> DataFrame:
    """The pairs (query, member) whose parities do not rule them out; marks: doc_id, n, parity."""
    own = pairs.join(marks.toDF("query", "qn", "qparity"), "query")
    both = own.join(marks.toDF("member", "mn", "mparity"), "member")
    return both.where(~_at_odds("qparity", "mparity", "qn", "mn")).select("query", "member").distinct()


def _answer(key: tuple, table: pa.Table) -> pa.Table:
    queries, members = [], []
    for doc, query, data in zip(*(table.column(c).to_pylist() for c in ("doc_id", "is_query", "data")), strict=True):
        (queries if query else members).append((doc, np.frombuffer(data, np.uint64)))
    found = [(q, members[i][0]) for q, own in queries for i in alike(own, [s for _, s in members])]
    return pa.table({"a": pa.array([a for a, _ in found], pa.int64()), "b": pa.array([b for _, b in found], pa.int64())})


def verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs (query, member) that have the required overlap, as (a, b)."""
    counts = pairs.groupBy("query").agg(F.ceil(F.count("*") / GROUP).cast("int").alias("parts"))
    asked = pairs.join(counts, "query").withColumn("part", F.pmod(F.xxhash64("member"), "parts").cast("int"))
    members = asked.select("query", "part", F.col("member").alias("doc_id"), F.lit(False).alias("is_query"))
    queries = counts.select("query", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.col("query").alias("doc_id"), F.lit(True).alias("is_query"))
    return _with_sets(members.unionByName(queries), sets).groupBy("query", "part").applyInArrow(_answer, "a long, b long")


def _with_sets(rows: DataFrame, sets: DataFrame) -> DataFrame:
    """The rows with their documents' sets, which are dealt once at most: FEW rows or less are sent to them instead."""
    asked = durable(rows)
    return sets.join(F.broadcast(asked) if asked.count() <= FEW else asked, "doc_id")


def classes(vertices: DataFrame, edges: DataFrame) -> DataFrame:
    """(doc_id, comp): the smallest doc_id that links reach. Edges are (a, b), in any direction.

    Each round a vertex takes the smallest label that a neighbour has and offers it to the vertex
    that its old label names, so that whole trees are hooked at their roots; labels are then looked up
    at labels. So the rounds grow with the logarithm of the longest chain.
    """
    both = durable(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct())
    labels = durable(both.groupBy(F.col("a").alias("doc_id")).agg(F.least(F.col("a"), F.min("b")).alias("comp")))
    none = F.lit(None).cast("long")
    while True:
        near = both.join(labels.withColumnRenamed("doc_id", "b"), "b").groupBy(F.col("a").alias("doc_id")).agg(F.min("comp").alias("seen"))
        offers = labels.join(near, "doc_id").select(F.explode(F.array(F.struct("doc_id", F.col("comp").alias("old"), F.least("comp", "seen").alias("low")), F.struct(F.col("comp").alias("doc_id"), none.alias("old"), F.least("comp", "seen").alias("low")))).alias("o"))
        taken = offers.select("o.*").groupBy("doc_id").agg(F.min("low").alias("low"), F.max("old").alias("old"))
        at = labels.select(F.col("doc_id").alias("low"), F.col("comp").alias("lower"))
        following = durable(taken.join(at, "low").select("doc_id", F.least("low", "lower").alias("comp"), "old"))
        labels = following.select("doc_id", "comp")
        if not following.where("comp <> old").take(1):
            break
    return vertices.join(labels, "doc_id", "left").select("doc_id", F.coalesce("comp", "doc_id").alias("comp"))


def _fits(n: str, place: str, m: str, other: str) -> Column:
    """Whether sets of n and m hashes can be alike when their first common hash is at these places."""
    need = F.expr(f"-((-{PERCENT} * ({n} + {m})) div {100 + PERCENT})")
    need = F.when(F.expr(f"{PERCENT} * ({n} + {m}) % {100 + PERCENT} = 0"), need).otherwise(need + 1)
    return F.least(F.col(n) - F.col(place), F.col(m) - F.col(other)) >= need


def _central(held: DataFrame) -> DataFrame:
    """Pairs of each entry's most central document with its documents of other classes."""
    some = held.groupBy("entry").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.min(F.struct("own", "doc_id", "n", "comp", "place")).alias("q")).where("lo <> hi").select("entry", "q.doc_id", "q.n", "q.comp", "q.place")
    asking = some.toDF("entry", "query", "qn", "qc", "qplace")
    found = held.join(asking, "entry").where(F.col("comp") != F.col("qc")).where(_fits("n", "place", "qn", "qplace"))
    return found.select("query", F.col("doc_id").alias("member")).distinct()


def _mixed(held: DataFrame) -> DataFrame:
    """Holders of the entries that documents of different classes hold, with the entry's number of holders."""
    mixed = held.groupBy("entry").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.count("*").alias("holders")).where("lo <> hi").select("entry", "holders")
    return held.join(mixed, "entry")


def _rest(holders: DataFrame) -> DataFrame:
    """The pairs of different classes in entries of LIGHT documents at most that may be alike by their common entry."""
    light = holders.where(F.col("holders") <= LIGHT)
    left = light.select("entry", F.col("doc_id").alias("query"), F.col("n").alias("qn"), F.col("comp").alias("qc"), F.col("place").alias("qplace"))
    found = left.join(light, "entry").where((F.col("query") < F.col("doc_id")) & (F.col("qc") != F.col("comp"))).where(_fits("n", "place", "qn", "qplace"))
    return found.select("query", F.col("doc_id").alias("member")).distinct()


def _search_tile(key: tuple, table: pa.Table) -> pa.Table:
    """Every document of one part asks the lists of the other; of one part alone, each asks those after it."""
    _, low, high = (k.as_py() for k in key)
    rows = sorted(zip(*(table.column(c).to_pylist() for c in ("doc_id", "part", "comp", "n", "place", "data")), strict=True), key=lambda r: r[0])
    found = []
    for doc, part, comp, n, place, data in rows:
        if part != low:
            continue
        others = [r for r in rows if r[1] == high and r[2] != comp and (low != high or r[0] > doc) and min(n - place, r[3] - r[4]) >= required(n, r[3])]
        found += [(doc, others[i][0]) for i in alike(np.frombuffer(data, np.uint64), [np.frombuffer(r[5], np.uint64) for r in others])]
    return pa.table({"a": pa.array([a for a, _ in found], pa.int64()), "b": pa.array([b for _, b in found], pa.int64())})


def _hopeful_tile(key: tuple, table: pa.Table) -> pa.Table:
    """The documents of a tile that have a partner there which neither their places nor their parities rule out."""
    entry, low, high = (k.as_py() for k in key)
    column = lambda c: table.column(c).to_numpy()
    doc, part, comp, n, left = column("doc_id"), column("part"), column("comp"), column("n"), column("n") - column("place")
    parity = table.column("parity").combine_chunks()
    words, starts = parity.values.to_numpy(), parity.offsets.to_numpy()
    sizes = np.diff(starts)
    others = [np.flatnonzero((sizes == s) & (part == high)) for s in np.unique(sizes)]
    kinds = [(rows, words[starts[rows][:, None] + np.arange(sizes[rows[0]])]) for rows in others if len(rows)]
    hopeful = np.zeros(len(doc), bool)
    for i in np.flatnonzero(part == low):
        mine = words[starts[i] : starts[i + 1]]
        for rows, theirs in kinds:
            need = -(-PERCENT * (n[i] + n[rows]) // (100 + PERCENT))
            fit = (comp[rows] != comp[i]) & (np.minimum(left[i], left[rows]) >= need)
            if fit.any():
                near = rows[fit][differing(mine, theirs[fit]) <= n[i] + n[rows[fit]] - 2 * need[fit]]
                hopeful[near] = True
                hopeful[i] |= len(near) > 0
    found = np.unique(doc[hopeful])
    same = lambda x, kind: pa.array(np.full(len(found), x), kind)
    return pa.table({"entry": same(entry, pa.int64()), "low": same(low, pa.int32()), "high": same(high, pa.int32()), "doc_id": pa.array(found, pa.int64())})


def _searched(holders: DataFrame, sets: DataFrame, marks: DataFrame) -> DataFrame:
    """The linked pairs of different classes in frequent entries, as (a, b): two parts of an entry's holders a task."""
    heavy = holders.where(F.col("holders") > LIGHT).withColumn("parts", F.ceil(F.col("holders") / (2 * GROUP)).cast("int"))
    own = heavy.withColumn("part", F.pmod(F.xxhash64("doc_id"), "parts").cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    tiles = durable(own.select("entry", F.least("part", "other").alias("low"), F.greatest("part", "other").alias("high"), "doc_id", "part", "comp", "n", "place"))
    hopeful = tiles.join(marks.select("doc_id", "parity"), "doc_id").groupBy("entry", "low", "high").applyInArrow(_hopeful_tile, "entry long, low int, high int, doc_id long")
    dealt = _with_sets(tiles.join(durable(hopeful), ["entry", "low", "high", "doc_id"]), sets)
    return dealt.groupBy("entry", "low", "high").applyInArrow(_search_tile, "a long, b long")


def linked(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles and component_id of every row."""
    dealt, exchange = deal(docs)
    buckets = exchange.buckets

    def candidates(key: tuple, rows: pa.Table, told: pa.Table) -> pa.Table:
        codes, grades = known(told, buckets)
        out: dict[str, list] = {c: [] for c in ("doc_id", "n", "same", "own", "entries", "places", "parity", "data")}
        seen: dict[tuple[int, bytes], int] = {}
        for texts, keys in chunks(rows, "doc_id"):
            for doc, own in zip(keys, shingle_sets(texts), strict=True):
                prefix, place, alone = entries(own, codes, grades, buckets) if doc is not None else (own[:0], own[:0], 0)
                data, first = None, doc
                if len(prefix):
                    data = own.tobytes()
                    first = seen.setdefault((len(own), data[:64] + _digest(data)), doc)
                chosen = data is not None and first == doc
                out["doc_id"].append(doc)
                out["n"].append(len(own))
                out["same"].append(first)  # one of a block's equal sets stands for all
                out["own"].append(alone / max(1, len(own)))
                out["entries"].append(prefix.view(np.int64).tolist() if chosen else None)
                out["places"].append(place.tolist() if chosen else None)
                out["parity"].append(parities(own) if chosen else None)
                out["data"].append(data if chosen else None)
        give_back()
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.list_(pa.int64()), pa.list_(pa.int32()), pa.list_(pa.int64()), pa.binary())
        return pa.table([pa.array(v, k) for v, k in zip(out.values(), kinds, strict=True)], names=list(out))

    told = shared(dealt, shingle_sets, exchange)
    every = durable(dealt.groupBy("block").cogroup(told.groupBy("a")).applyInArrow(candidates, "doc_id long, n long, same long, own double, entries array<long>, places array<int>, parity array<long>, data binary"))
    some = every.where("data IS NOT NULL")
    sets, marks = some.select("doc_id", "data"), some.select("doc_id", "n", "parity")
    held = some.select("doc_id", "n", "own", F.explode(F.arrays_zip("entries", "places")).alias("e")).select("doc_id", "n", "own", F.col("e.entries").alias("entry"), F.col("e.places").alias("place"))
    vertices = every.where("doc_id IS NOT NULL").select("doc_id").distinct()
    links = every.where("same <> doc_id").select(F.col("same").alias("a"), F.col("doc_id").alias("b"))
    first = verified(durable(plausible(_central(held.withColumn("comp", F.col("doc_id"))), marks)), sets)
    links = durable(links.unionByName(first))
    comp = durable(classes(vertices, links))
    holders = durable(_mixed(held.join(comp, "doc_id")))
    more = durable(verified(durable(plausible(_rest(holders), marks)), sets).unionByName(_searched(holders, sets, marks)).distinct())
    if more.take(1):  # classes of classes
        at = lambda c: comp.select(F.col("doc_id").alias(c), F.col("comp").alias(f"{c}c"))
        joined = more.join(at("a"), "a").join(at("b"), "b").select(F.col("ac").alias("a"), F.col("bc").alias("b"))
        lower = classes(comp.select(F.col("comp").alias("doc_id")).distinct(), joined).select(F.col("doc_id").alias("comp"), F.col("comp").alias("lowest"))
        # A class may hold a third of all rows: its rows meet its new name in SALTS tasks.
        salted = lower.where("comp <> lowest").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        spread = comp.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(SALTS)).cast("int"))
        comp = durable(spread.join(salted, ["comp", "salt"], "left").select("doc_id", F.coalesce("lowest", "comp").alias("comp")))
    return every.join(comp, "doc_id", "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("comp", "doc_id").alias("component_id"))


def _digest(data: bytes) -> bytes:
    import hashlib

    return hashlib.blake2b(data, digest_size=16).digest()


#: The same in DuckDB: overlaps by counting shared shingles, classes by a recursive walk.
ORACLE = r"""
WITH RECURSIVE split AS (
    SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents
), shingles AS (
    SELECT DISTINCT doc_id, CASE WHEN len(ws) < 5 THEN array_to_string(ws, ' ') ELSE array_to_string(ws[i:i + 4], ' ') END AS g
    FROM split, unnest(range(1, greatest(2, len(ws) - 3))) u(i) WHERE len(ws) > 0
), sizes AS (
    SELECT doc_id, count(*) AS n FROM shingles GROUP BY doc_id
), common AS (
    SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM shingles a JOIN shingles b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL
), links AS (
    SELECT a, b FROM common JOIN sizes x ON x.doc_id = a JOIN sizes y ON y.doc_id = b WHERE 100 * c >= 80 * (x.n + y.n - c)
), reach(doc_id, seen) AS (
    SELECT doc_id, doc_id FROM documents UNION SELECT links.b, reach.seen FROM reach JOIN links ON links.a = reach.doc_id
)
SELECT reach.doc_id, coalesce(any_value(sizes.n), 0)::BIGINT AS n_shingles, min(seen) AS component_id FROM reach LEFT JOIN sizes USING (doc_id) GROUP BY reach.doc_id
"""
