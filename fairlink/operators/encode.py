"""Bloom filter encoding at the owner: map-only projections, no exchange."""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fairlink.functions import bits, rng, tokens
from fairlink.settings import DEFAULT, WORDS, Linkage
from fairlink.sources.steps import spread

VOTER = (("given", "g:"), ("surname", "s:"), ("suburb", "b:"), ("postcode", "p:"))


def voter_tokens(q: int = 2) -> Column:
    """Substring tokens of the names and places, and the gender as a whole."""
    parts = [tokens.qgrams(F.col(c), p, q) for c, p in VOTER]
    return F.array_distinct(F.concat(*parts, tokens.exact(F.col("gender"), "x:")))


def census_tokens() -> Column:
    """Whole values of the categorical attributes and each industry."""
    whole = [tokens.exact(F.col(c), p) for c, p in (("area", "a:"), ("mesh", "m:"), ("gender", "x:"), ("full_time", "f:"))]
    return F.array_distinct(F.concat(*whole, tokens.each(F.col("industries"), "i:")))


def token_positions(token_array: Column, k: int, n_bits: int, secret: str) -> Column:
    """Filter positions by double hashing of each keyed token."""

    def places(token: Column) -> Column:
        keyed = F.concat(F.lit(f"{secret}|"), token)
        pair = F.struct(rng.whole(keyed).alias("a"), rng.whole(keyed, rng.DIGITS + 1).alias("b"))
        one = F.get(F.transform(F.array(pair), lambda h: F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda i: F.pmod(h["a"] + i * h["b"], F.lit(n_bits).cast("long")))), 0)
        return one

    return F.array_distinct(F.flatten(F.transform(token_array, places)))


def bloom(df: DataFrame, token_array: Column, settings: Linkage = DEFAULT, rounds: int = 1) -> DataFrame:
    """Adds w0.. and n_ones. With more rounds the tokens are hashed with so many secrets into one filter."""
    secrets = [settings.secret if r == 0 else f"{settings.secret}#{r}" for r in range(rounds)]
    places = [token_positions(F.col("_tokens"), settings.k_hash, settings.n_bits, s) for s in secrets]
    placed = df.withColumn("_tokens", token_array).withColumn("_places", F.array_distinct(F.concat(*places)))
    made = placed.withColumns({f"w{i}": bits.word_of(F.col("_places"), i) for i in range(WORDS)})
    return made.withColumn("n_ones", bits.ones().cast("int")).drop("_tokens", "_places")


#: Attributes of the learned classifiers, each with its tokens: q-grams, whole values, or one token an element.
ATTRIBUTES = {
    False: (("given", "g:", "grams"), ("surname", "s:", "grams"), ("suburb", "b:", "grams"), ("postcode", "p:", "grams"), ("gender", "x:", "whole")),
    True: (("area", "a:", "whole"), ("mesh", "m:", "whole"), ("gender", "x:", "whole"), ("full_time", "f:", "whole"), ("industries", "i:", "each")),
}
ATTRIBUTE_HASHES = 30


def attribute_tokens(name: str, prefix: str, kind: str, q: int = 2) -> Column:
    if kind == "grams":
        return tokens.qgrams(F.col(name), prefix, q)
    return tokens.exact(F.col(name).cast("string"), prefix) if kind == "whole" else tokens.each(F.col(name), prefix)


def bloom_attributes(df: DataFrame, settings: Linkage = DEFAULT, census: bool = False, k_hash: int = ATTRIBUTE_HASHES) -> DataFrame:
    """One filter per attribute: words t0w0, t0w1, .. of the first, t1w0, .. of the second, and so on."""
    for j, spec in enumerate(ATTRIBUTES[census]):
        df = df.withColumn("_places", token_positions(attribute_tokens(*spec, settings.q), k_hash, settings.n_bits, settings.secret))
        df = df.withColumns({f"t{j}w{i}": bits.word_of(F.col("_places"), i) for i in range(WORDS)}).drop("_places")
    return df


def mean_tokens(df: DataFrame, token_array: Column) -> DataFrame:
    return df.agg(F.avg(F.size(token_array)).alias("mean_tokens"))


def auto_k(mean: float, n_bits: int = 300) -> int:
    """The number of hash functions that fills half of the filter."""
    return max(1, math.floor(n_bits * math.log(2) / max(mean, 1e-9) + 0.5))


def fill_stats(encoded: DataFrame, n_bits: int = 300) -> DataFrame:
    """Per party rows, mean and deviation of the share of ones."""
    share = F.col("n_ones") / n_bits
    return encoded.groupBy("party").agg(F.count("*").alias("n"), F.avg(share).alias("fill"), F.stddev_pop(share).alias("fill_sd"))


def sign_bits(vector: Column, words: int = 2) -> list[Column]:
    """Words whose bit i says whether element i of the vector is positive."""
    out = []
    for w in range(words):
        part = F.slice(vector, w * 60 + 1, 60)
        out.append(F.aggregate(F.transform(part, lambda x, i: F.when(x > 0, F.call_function("shiftleft", F.lit(1).cast("long"), i)).otherwise(F.lit(0).cast("long"))), F.lit(0).cast("long"), lambda a, x: a.bitwiseOR(x)))
    return out


def encoded(parties: DataFrame, settings: Linkage = DEFAULT, census: bool = False, rounds: int = 1, attributes: bool = False) -> DataFrame:
    """party, rec_id, entity_id (tests only), group_id, w0.., n_ones, and t0w0.. where attributes are asked for."""
    if attributes:
        parties = bloom_attributes(parties, settings, census)
    made = bloom(parties, census_tokens() if census else voter_tokens(settings.q), settings, rounds)
    own = [c for c in made.columns if c[0] == "t" and c[1:2].isdigit()]
    return made.select("party", "rec_id", "entity_id", "group_id", *bits.names(), "n_ones", *own)


def encoded_values(parties: DataFrame, settings: Linkage = DEFAULT, rounds: int = 1, attributes: bool = False, more: tuple[str, ...] = ()) -> DataFrame:
    """As encoded, with more columns where they are asked for; each value of an attribute is hashed once, and a record's filter is put together from those of its values."""
    secrets = [settings.secret if r == 0 else f"{settings.secret}#{r}" for r in range(rounds)]
    for j, (name, prefix, kind) in enumerate(ATTRIBUTES[False]):
        made = spread(parties.select(name).distinct(), name)
        sets = [("v", F.array_distinct(F.concat(*(token_positions(attribute_tokens(name, prefix, kind, settings.q), settings.k_hash, settings.n_bits, s) for s in secrets))))]
        if attributes:
            sets.append(("t", token_positions(attribute_tokens(name, prefix, kind, settings.q), ATTRIBUTE_HASHES, settings.n_bits, settings.secret)))
        for mark, places in sets:
            made = made.withColumn("_places", places).withColumns({f"{mark}{j}w{i}": bits.word_of(F.col("_places"), i) for i in range(WORDS)}).drop("_places")
        parties = parties.join(made.withColumnRenamed(name, "_value"), F.col(name).eqNullSafe(F.col("_value"))).drop("_value")
    word = lambda i: reduce(lambda x, y: x.bitwiseOR(y), [F.col(f"v{j}w{i}") for j in range(len(ATTRIBUTES[False]))])
    parties = parties.withColumns({f"w{i}": word(i) for i in range(WORDS)}).withColumn("n_ones", bits.ones().cast("int"))
    own = [c for c in parties.columns if c[0] == "t" and c[1:2].isdigit()]
    return parties.select("party", "rec_id", "entity_id", "group_id", *bits.names(), "n_ones", *own, *more)


def encoded_census(parties: DataFrame, settings: Linkage = DEFAULT, rounds: int = 1, attributes: bool = False) -> DataFrame:
    """As encoded; each combination of the categorical attributes is hashed once, for few of them make up all records."""
    names = [name for name, *_ in ATTRIBUTES[True]]
    made = parties.select(*names).distinct()
    if attributes:
        made = bloom_attributes(made, settings, True)
    made = bloom(made, census_tokens(), settings, rounds)
    own = [c for c in made.columns if c[0] == "t" and c[1:2].isdigit()]
    made = made.select(*(F.col(c).alias(f"_{c}") for c in names), *bits.names(), "n_ones", *own)
    same = [F.col(c).eqNullSafe(F.col(f"_{c}")) for c in names]
    return parties.join(made, same).select("party", "rec_id", "entity_id", "group_id", *bits.names(), "n_ones", *own)
