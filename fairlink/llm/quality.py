"""Quality rules compiled from a threshold table into one projection of built-in functions.

A rule bounds one count by another: low * whole <= 100 * part <= high * whole, in whole numbers, so
that every engine decides alike. `measure` gives the counts of a text in one pass over its words,
`verdict` the conjunction of all rules. No user function runs and no row moves.

Words are maximal runs without ASCII white space. Null and empty texts have no words and fail the
base rules. Windows of eight words are compared by a 64-bit hash within one text.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fairlink.llm.common import text_or_empty

SPACES = " \t\n\x0b\f\r"
SPLIT = r"[\x20\x09-\x0D]+"
SYMBOLS = r"[#*$%&|<>]"
WINDOW = 8

#: Fixed list of frequent function words: English, German, French, Spanish.
STOP_WORDS = tuple(
    """the of and to a in is that for on with as was by at it from this be are not or an he she they we you which his her have has had
    der die das und in von zu den mit sich des auf für ist im dem nicht ein eine als auch es an werden aus er hat dass sie nach wird bei
    le la les de des et en un une du que qui dans pour est au sur pas par avec ne se ce il elle sont plus ou mais
    el los las y del se por con para una su al lo como más pero sus no este ya o si porque cuando""".split()
)


@dataclass(frozen=True)
class Rule:
    """Bounds in hundredths of `whole` for `part`; None is no bound."""

    name: str
    part: str
    whole: str
    low: int | None = None
    high: int | None = None

    def terms(self) -> list[tuple[str, int, str, str]]:
        return [(a, b, c, d) for a, b, c, d in ((self.part, self.low, self.whole, ">="), (self.part, self.high, self.whole, "<=")) if b is not None]

    def sql(self) -> str:
        return " AND ".join(f"100 * {part} {sign} {bound} * {whole}" for part, bound, whole, sign in self.terms())


#: The contract's base: too short, or mostly made of repeated passages.
BASE = (Rule("words", "n_words", "1", low=2000), Rule("repeated_words", "n_repeat_words", "n_words", high=30))
#: The method's own table.
TABLE = (
    Rule("word_length", "word_chars", "n_words", low=200, high=1400),
    Rule("symbols", "n_symbols", "n_words", high=10),
    Rule("stop_words", "n_stop_words", "n_words", low=2),
    Rule("repeated_lines", "n_dup_lines", "n_lines", high=50),
    Rule("capitals", "n_capitals", "word_chars", high=30),
    Rule("adjacent_repeats", "n_adjacent", "n_words", high=20),
)


def bound(value: Column, use) -> Column:
    """use(x) with x bound to the value, which is then computed once."""
    return F.get(F.transform(F.array(value), use), 0)


def words_of(text: Column) -> Column:
    inner = F.btrim(text, F.lit(SPACES))
    return F.when(inner == "", F.array().cast("array<string>")).otherwise(F.split(inner, SPLIT))


def repeated(words: Column) -> Column:
    """Number of words that lie in windows found twice or more."""

    def covered(hashes: Column) -> Column:
        def runs(pairs: Column) -> Column:
            again = F.filter(pairs, lambda x, k: F.coalesce(F.get(pairs, k - 1)["h"] == x["h"], F.lit(False)) | F.coalesce(F.get(pairs, k + 1)["h"] == x["h"], F.lit(False)))
            places = F.sort_array(F.transform(again, lambda x: x["i"]))
            none = F.struct(F.lit(0).alias("n"), F.lit(0).alias("reach"))
            return F.aggregate(places, none, lambda a, p: F.struct((a["n"] + p + WINDOW - F.greatest(p, a["reach"])).alias("n"), (p + WINDOW).alias("reach")), lambda a: a["n"])

        pairs = F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(hashes)) == F.size(hashes), 0).otherwise(bound(pairs, runs))

    def windows(codes: Column) -> Column:
        starts = F.sequence(F.lit(1), F.size(codes) - (WINDOW - 1))
        return F.transform(starts, lambda i: F.xxhash64(F.slice(codes, i, WINDOW)))

    many = F.size(words) > WINDOW
    return F.when(many, bound(bound(F.transform(words, lambda w: F.xxhash64(w)), windows), covered)).otherwise(0)


def measure(text: Column) -> Column:
    """All counts of the rules, as one struct."""
    worded = F.filter(F.split(text, "\n", -1), lambda line: line.rlike(r"[^\x20\x09-\x0D]"))
    listed = [*STOP_WORDS, *(w.capitalize() for w in STOP_WORDS)]

    def counts(words: Column) -> Column:
        own = {
            "n_words": F.size(words),
            "word_chars": F.length(F.array_join(words, "")),
            "n_symbols": F.regexp_count(text, F.lit(SYMBOLS)),
            "n_repeat_words": repeated(words),
            "n_stop_words": F.size(F.filter(words, lambda w: w.isin(listed))),
            "n_capitals": F.regexp_count(text, F.lit(r"\p{Lu}")),
            "n_adjacent": F.size(F.filter(words, lambda w, i: (i > 0) & (w == F.coalesce(F.get(words, i - 1), F.lit(""))))),
        }
        return F.struct(*(c.cast("long").alias(k) for k, c in own.items()))

    lines = bound(worded, lambda x: F.struct(F.size(x).cast("long").alias("n_lines"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines")))
    return F.struct(bound(words_of(text), counts).alias("w"), lines.alias("l"))


def judge(docs: DataFrame) -> DataFrame:
    """One row per document: its counts, whether the base rules fail it, and whether it is kept."""
    passes = lambda rules: F.expr(" AND ".join(f"({r.sql()})" for r in rules))
    counted = docs.select("doc_id", measure(text_or_empty()).alias("m")).select("doc_id", "m.w.*", "m.l.*")
    judged = counted.withColumn("base_failed", ~passes(BASE)).withColumn("kept", ~F.col("base_failed") & passes(TABLE))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_stop_words", "n_capitals", "n_adjacent", "n_lines")


def oracle() -> str:
    """The same in DuckDB, counted by unnested rows."""
    listed = ", ".join("'" + w + "'" for w in dict.fromkeys([*STOP_WORDS, *(w.capitalize() for w in STOP_WORDS)]))
    both = lambda rules: " AND ".join(f"({r.sql()})" for r in rules)
    return rf"""
    WITH split AS (
        SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents
    ), grams AS (
        SELECT doc_id, i, array_to_string(ws[i:i + 7], ' ') AS g FROM split, unnest(range(1, len(ws) - 6)) u(i)
    ), twice AS (
        SELECT doc_id, i FROM grams QUALIFY count(*) OVER (PARTITION BY doc_id, g) > 1
    ), covered AS (
        SELECT doc_id, count(DISTINCT i + k) AS n FROM twice, range(8) r(k) GROUP BY doc_id
    ), lined AS (
        SELECT doc_id, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM split
    ), counted AS (
        SELECT split.doc_id, len(ws)::BIGINT AS n_words,
            coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0)::BIGINT AS word_chars,
            len(regexp_extract_all(t, '[#*$%&|<>]'))::BIGINT AS n_symbols,
            (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines,
            coalesce(covered.n, 0)::BIGINT AS n_repeat_words,
            len(list_filter(ws, lambda x: x IN ({listed})))::BIGINT AS n_stop_words,
            len(regexp_extract_all(t, '\p{{Lu}}'))::BIGINT AS n_capitals,
            len(list_filter(ws, lambda x, i: i > 1 AND x = ws[i - 1]))::BIGINT AS n_adjacent,
            len(ls)::BIGINT AS n_lines
        FROM split JOIN lined USING (doc_id) LEFT JOIN covered USING (doc_id)
    )
    SELECT *, NOT ({both(BASE)}) AS base_failed, ({both(BASE)}) AND {both(TABLE)} AS kept FROM counted
    """
