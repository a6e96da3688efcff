"""Secret scans with a random forest against false positives, in built-in functions only.

A candidate is a word with a long run of key characters that mixes digits and letters, a long run of letters,
a value of six characters or more that follows a credential name with = or :, in the same word or in the one or two
words before, or the password of an address with user and host. Its value is what follows the = or : and quote. Features of a candidate:
length, shares of digits and capitals, transitions (between any character classes, from letters to digits and back, from
small letters to capitals, runs of consonants), distinct characters, whether it is all hexadecimal, how much of it the
corpus's own frequent words cover, marks of paths and addresses, known key prefixes, marks as passwords hold them, whether it is
assigned to a credential name, and whether the words before and beside it speak of credentials, of digests and versions, or look like keys themselves.

The dictionary holds the DICTIONARY most frequent words of four letters or more of all documents, counted by Spark; as a
pattern it goes into the features. The forest is trained by Spark's own learner on labelled findings that a rule makes from keyed
hashes and the dictionary's words: keys, tokens and passwords against digests, identifiers, paths, versions and
ordinary words, TRAIN_ROWS rows. Its trees become nested conditions, so that finding, scoring and
masking are one projection over the whole text: no row moves and no user function runs.

Null and empty texts have no findings. A value that occurs twice in a text is found twice and masked everywhere. Without
documents the dictionary is that of no word.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.ml.classification import RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fairlink.llm.common import text_or_empty
from fairlink.llm.quality import bound, words_of

TRAIN_ROWS = 8_000
DICTIONARY = 400
TREES = 15
DEPTH = 6
SHORTEST = 12
MASK = "[SECRET]"

# Fixed lists and patterns.
CREDENTIAL = r"(?i)(pass(word|wd|phrase)?|pwd|secret|token|api[_-]?key|auth|bearer|credential|private[ _-]?key|access[_-]?key|client[_-]?secret|kennwort|passwort|contraseña|clave|mot[_ ]de[_ ]passe)"
BENIGN = r"(?i)(commit|sha-?\d*|md5|checksum|digest|hash|etag|uuid|guid|version|revision|build|isbn|issn|doi|order|invoice|serial|phone|tel|image|file|path|example|sample|placeholder)"
PREFIXES = r"^(AKIA|ASIA|ghp_|gho_|ghs_|github_pat_|glpat-|sk-|sk_live_|rk_live_|xox[abpr]-|AIza|eyJ|SG\.|npm_|pypi-)"
#: Words of source texts and addresses that count as known besides the corpus's own.
TECHNICAL = ("user", "name", "file", "page", "http", "html", "image", "data", "test", "index", "mail", "example", "password", "string", "config", "value")
NAMED = CREDENTIAL + r"(?!or|ent|age|eng|ion|iv|ari?[yae])[A-Za-z0-9_.\-]*[\"'`\])]*"
ASSIGNED = NAMED + r"[=:][=:>]*[\"'`]?\S{6,}"
AWAITING = NAMED + r" ?[=:][=:>]*[\"'`]?$"
KEYLIKE = r"(?=[^\s]*[0-9])(?=[^\s]*[A-Za-z])[A-Za-z0-9+/_.\-]{16,}"
LETTERS = r"[A-Za-z]{20,}"
LOGIN = r"^[\"'(<\[]*[A-Za-z][A-Za-z0-9+.\-]*://[^\s:/@]*:([^\s@/]{4,})@"

FEATURES = (
    "size", "digits", "capitals", "changes", "to_digit", "to_letter", "to_capital", "clusters", "distinct", "hexadecimal", "covered", "path", "prefix", "credential", "benign", "dashes", "named", "marks", "beside"
)


def dictionary(docs: DataFrame, size: int = DICTIONARY) -> list[str]:
    """The most frequent words of four to twelve letters of all texts; ties in order of the words."""
    words = docs.select(F.explode(F.split(F.lower("text"), r"[^\p{L}]+")).alias("word")).where(F.length("word").between(4, 12))
    top = words.groupBy("word").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "word").limit(size)
    return [r["word"] for r in top.collect()]


def known(words: list[str]) -> str:
    """A pattern of the words, the longer ones first."""
    return "(?iu)(" + "|".join(sorted({*words, *TECHNICAL}, key=lambda w: (-len(w), w))) + ")"


def awaited(before: Column, word: Column) -> Column:
    """Whether the words before are a credential name with = or :, which may begin the word itself."""
    return before.rlike(AWAITING) | (before.rlike(NAMED + "$") & word.rlike(r"^[=:]"))


def value_of(word: Column, before: Column) -> Column:
    """The candidate's value: without the name before = or :, quotes and closing marks."""
    bare = F.regexp_replace(word, r"^[\"'(<\[]+|[^A-Za-z0-9+/_\-]+$", "")
    free = F.regexp_replace(bare, r"^[A-Za-z_][A-Za-z0-9_.\-]*[\"']?[=:]+[\"']?(?=.{6,})", "")
    # What is assigned to a credential name may hold any mark, but for the quotes and stops around it.
    closed = F.regexp_replace(word, r"[\"'`)\]}>,;.]+$", "")
    after = F.regexp_replace(closed, r"^[=:>]*[\"'`(<\[]*", "")
    own = F.regexp_replace(closed, "^.*?" + NAMED + r"[=:][=:>]*[\"'`]?(?=.{6,})", "")
    return F.when(word.rlike(LOGIN), F.regexp_extract(word, LOGIN, 1)).when(word.rlike(ASSIGNED), own).when(awaited(before, word), after).otherwise(free)


def features(value: Column, before: Column, word: Column, words: str) -> Column:
    """The features of a candidate value, the words before it, and its own word; words: the dictionary's pattern."""
    n = F.length(value).cast("double")
    share = lambda pattern: F.regexp_count(value, F.lit(pattern)) / F.greatest(n, F.lit(1.0))
    yes = lambda c: c.cast("double")
    around = F.concat_ws(" ", before, F.regexp_extract(word, r"^([^=:]*[=:])", 1))
    shape = F.regexp_replace(F.regexp_replace(F.regexp_replace(value, "[a-z]+", "a"), "[A-Z]+", "B"), "[0-9]+", "0")
    return F.struct(
        n.alias("size"),
        share("[0-9]").alias("digits"),
        share("[A-Z]").alias("capitals"),
        (F.length(shape) / F.greatest(n, F.lit(1.0))).alias("changes"),
        share("[A-Za-z][0-9]").alias("to_digit"),
        share("[0-9][A-Za-z]").alias("to_letter"),
        share("[a-z][A-Z]").alias("to_capital"),
        share("(?i)[bcdfghjklmnpqrstvwxz]{4}").alias("clusters"),
        (F.size(F.array_distinct(F.split(value, ""))) / F.greatest(n, F.lit(1.0))).alias("distinct"),
        yes(value.rlike("^[0-9a-fA-F]+$")).alias("hexadecimal"),
        (1 - F.length(F.regexp_replace(value, words, "")) / F.greatest(n, F.lit(1.0))).alias("covered"),
        yes(value.rlike(r"(/[^/]+/)|(^\.{0,2}/)|(\.[a-z]{2,4}$)|(://)|(^www\.)|@")).alias("path"),
        yes(value.rlike(PREFIXES)).alias("prefix"),
        yes(around.rlike(CREDENTIAL)).alias("credential"),
        yes(around.rlike(BENIGN)).alias("benign"),
        share(r"[\-]").alias("dashes"),
        yes(word.rlike(ASSIGNED) | awaited(before, word) | word.rlike(LOGIN)).alias("named"),
        share(r"[!@#$%^&*~?]").alias("marks"),
        yes(before.rlike(r"(-----$)|((^| )[A-Za-z0-9+/]{40,}$)")).alias("beside"),
    )


def labelled(spark: SparkSession, words: list[str], rows: int = TRAIN_ROWS) -> DataFrame:
    """(value, before, word, label): findings made by rule, about half of them true secrets; words: the dictionary."""
    common = words or list(TECHNICAL)
    seed = F.col("id").cast("string")
    hexa = F.concat(F.sha2(F.concat(seed, F.lit("a")), 256), F.sha2(F.concat(seed, F.lit("b")), 256))
    mixed = F.regexp_replace(F.base64(F.unhex(hexa)), "[\r\n=]", "")
    digit = lambda salt, n: F.pmod(F.xxhash64("id", F.lit(salt)), F.lit(n)).cast("int")
    part = lambda c, low, high: F.substr(c, F.lit(1), digit(f"n{low}{high}", high - low + 1) + low)
    pick = lambda salt, *options: F.get(F.array(*map(F.lit, options)), digit(salt, len(options)))
    name = pick("name", "password", "token", "secret", "api_key", "access_key", "pwd", "auth_token", "client_secret")
    plain = pick("plain", "the", "of", "und", "que", "see", "with", "la", "for", "in", "est")
    some = lambda salt: pick(salt, *common)
    tag = pick("tag", "commit", "sha256:", "md5", "checksum", "uuid", "version", "build", "etag", "file", "order")
    long = F.concat(*(pick(f"w{i}", "thing", "ation", "ment", "heit", "sch", "que", "able", "er", "con", "pro", "lich", "ado") for i in range(5)))
    upper = F.upper(F.regexp_replace(mixed, "[^A-Za-z0-9]", ""))
    letters = F.regexp_replace(mixed, "[^A-Za-z]", "")
    plainer = pick("plainer", "required", "string", "optional", "wikipedia", "disabled", "enabled", "Bearer", "session", "expired", "invalid", "Schmidt", "example", "siehe", "unknown", "missing", "password", "changed", "obligatoire", "necesario", "garden")
    human = F.concat(pick("h", "Summer", "hunter", "dragon", "Tr0ub4dor", "s3cret", "monkey", "letme", "Winter", "p4ss", "qwer", "Sonne", "soleil", "sol", "abc"), pick("hs", "", "!", "&", "@", "_", "#", "Word"), digit("hd", 9999).cast("string"), pick("he", "", "!", "x", "$", "secret", "?"))
    human = F.rpad(human, F.greatest(F.length(human), F.lit(7)), "7")
    inner = F.concat(pick("i", "hunter", "dragon", "summer", "abc", "my", "Garten", "winter", "blue"), digit("id", 99).cast("string"), pick("ie", "secret", "word", "house", "moon", "river", "Haus", "xyz"))
    kinds = [  # value, words before, name in the same word, label
        (F.concat(F.lit("AKIA"), F.substr(upper, F.lit(1), F.lit(16))), plain, "", 1),
        (part(hexa, 16, 48), F.concat(name, F.lit(" =")), "", 1),
        (part(hexa, 12, 40), plain, "=", 1),
        (part(mixed, 20, 60), F.concat(name, F.lit(" :")), "", 1),
        (F.concat(pick("p", "ghp_", "sk-", "xoxb-", "AIza", "glpat-", "npm_"), part(mixed, 24, 40)), plain, "", 1),
        (F.concat(F.lit("eyJ"), part(mixed, 40, 80)), plain, "", 1),
        (part(mixed, 8, 20), plain, "=", 1),
        (part(hexa, 32, 64), tag, "", 0),
        (F.substr(hexa, F.lit(1), pick("len", 32, 40, 64)), plain, "", 0),
        (F.concat_ws("-", *(F.substr(hexa, F.lit(a), F.lit(n)) for a, n in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12)))), tag, "", 0),
        (F.concat(F.lit("/"), F.substr(long, F.lit(1), F.lit(9)), F.lit("/"), F.substr(hexa, F.lit(1), F.lit(6)), F.lit(".png")), plain, "", 0),
        (F.concat(F.lit("https://www."), F.substr(long, F.lit(1), F.lit(10)), F.lit(".example.com/p"), digit("u", 9999).cast("string")), plain, "", 0),
        (F.concat(long, digit("d", 99).cast("string")), plain, "", 0),
        (F.concat(long, F.lit("@mail"), digit("m", 9).cast("string"), F.lit(".example.com")), plain, "", 0),
        (F.concat(F.lit("v"), digit("v1", 30).cast("string"), F.lit("."), digit("v2", 30).cast("string"), F.lit(".0-"), F.substr(long, F.lit(1), F.lit(8))), tag, "", 0),
        (pick("ph", "your_password_here1", "example_token_0000", "xxxxxxxxxxxxxxxx1", "changeme12345678", "REPLACE_ME_00000000"), F.concat(name, F.lit(" =")), "", 0),
        (human, F.concat(plain, F.lit(" "), name, F.lit(":")), "", 1),
        (human, F.concat(name, F.lit(" =")), "", 1),
        (human, plain, "=", 1),
        (inner, F.concat(plain, F.lit(" "), name, F.lit(":")), "", 1),
        (inner, plain, "=", 1),
        (part(hexa, 8, 15), F.concat(plain, F.lit(" "), name, F.lit(":")), "", 1),
        (part(mixed, 8, 15), F.concat(name, F.lit(" =")), "", 1),
        (F.substr(F.regexp_replace(upper, "[0-9]", ""), F.lit(1), digit("ul", 20) + 14), F.concat(name, F.lit(" =")), "", 1),
        (F.substr(letters, F.lit(1), digit("ll", 20) + 12), F.concat(plain, F.lit(" "), name, F.lit(":")), "", 1),
        (F.substr(letters, F.lit(1), digit("lu", 20) + 24), plain, "", 1),
        (plainer, F.concat(plain, F.lit(" "), name, F.lit(":")), "", 0),
        (plainer, F.concat(name, F.lit(" =")), "", 0),
        (plainer, plain, "=", 0),
        (F.concat(long, long), plain, "", 0),
        (F.initcap(F.concat(long, long)), plain, "", 0),
        (long, F.concat(plain, F.lit(" "), name, F.lit(":")), "", 0),
        (F.concat(some("c1"), some("c2"), some("c3")), plain, "", 0),
        (F.concat_ws("-", some("c1"), some("c2"), digit("cn", 2030).cast("string"), some("c3")), plain, "", 0),
        (F.concat_ws("_", some("c1"), some("c2"), digit("cn", 99).cast("string")), plain, "", 0),
        (some("c1"), F.concat(plain, F.lit(" "), name, F.lit(":")), "", 0),
        (some("c1"), F.concat(name, F.lit(" =")), "", 0),
        (some("c1"), plain, "=", 0),
        (F.concat(some("c1"), digit("cd", 9999).cast("string"), pick("ce", "!", "#", "$", "?", "*")), F.concat(plain, F.lit(" "), name, F.lit(":")), "", 1),
        (F.concat(F.initcap(some("c1")), digit("cd", 9999).cast("string")), F.concat(name, F.lit(" =")), "", 1),
        (F.concat(F.initcap(some("c1")), pick("cf", "-", "_", "+", "."), some("c2"), digit("cd", 999).cast("string")), plain, "=", 1),
        (F.substr(F.concat(mixed, mixed), F.lit(1), digit("pem", 12) + 60), pick("pb", "RSA PRIVATE KEY-----", "PRIVATE KEY-----", "EC PRIVATE KEY-----"), "", 1),
        (F.substr(F.concat(mixed, mixed), F.lit(1), F.lit(64)), F.substr(F.concat(F.reverse(mixed), mixed), F.lit(1), F.lit(64)), "", 1),
        (F.substr(mixed, F.lit(1), digit("bx", 20) + 32), pick("bt", "Authorization: Bearer", "header Bearer", "auth token"), "", 1),
        (F.concat(F.substr(mixed, F.lit(1), F.lit(43)), F.lit("=")), pick("it", "integrity sha256-", "etag", "checksum", "sha512:"), "", 0),
        (human, plain, "login", 1),
        (F.concat(pick("fn", "get_", "os.environ.", "self.", "config.", "read_", "your_", "my_"), pick("fm", "password", "token", "secret", "api_key", "credentials", "settings")), F.concat(name, F.lit(" =")), "", 0),
    ]
    made = spark.range(rows).withColumn("kind", F.pmod(F.xxhash64("id", F.lit("kind")), F.lit(len(kinds))).cast("int"))
    at = lambda options: F.get(F.array(*options), F.col("kind"))
    made = made.select(at([k[0] for k in kinds]).alias("value"), at([k[1] for k in kinds]).alias("before"), at([F.lit(k[2]) for k in kinds]).alias("sign"), at([F.lit(float(k[3])) for k in kinds]).alias("label"), name.alias("name"))
    return made.select("value", "before", F.when(F.col("sign") == "login", F.concat(F.lit("db://admin:"), "value", F.lit("@host/x"))).when(F.col("sign") != "", F.concat("name", "sign", "value")).otherwise(F.col("value")).alias("word"), "label")


_SPLIT = re.compile(r"^ *If \(feature (\d+) <= ([-0-9.Ee]+)\)$")
_LEAF = re.compile(r"^ *Predict: ([0-9.]+)$")
_ELSE = re.compile(r"^ *Else \(feature ")


def tree_column(text: str, row: Column) -> Column:
    """A tree's printed form as nested conditions on the fields of a row of features."""
    lines = [x for x in text.splitlines() if _SPLIT.match(x) or _LEAF.match(x) or _ELSE.match(x)]
    at = 0

    def build() -> Column:
        nonlocal at
        line = lines[at]
        at += 1
        if m := _LEAF.match(line):
            return F.lit(float(m[1]))
        m = _SPLIT.match(line)
        yes = build()
        at += 1  # the Else line, which states the opposite
        return F.when(row[FEATURES[int(m[1])]] <= float(m[2]), yes).otherwise(build())

    return build()


@dataclass(frozen=True)
class Forest:
    """The trees in printed form, and the dictionary's pattern that their features need."""

    trees: tuple[str, ...]
    words: str


def train(docs: DataFrame, findings: DataFrame | None = None, trees: int = TREES, depth: int = DEPTH) -> Forest:
    """A forest for these documents. findings: (value, before, word, label), made by rule where none are given."""
    words = dictionary(docs)
    made = findings if findings is not None else labelled(docs.sparkSession, words)
    table = made.select(features(F.col("value"), F.col("before"), F.col("word"), known(words)).alias("f"), "label").select("f.*", "label")
    vectors = VectorAssembler(inputCols=list(FEATURES), outputCol="features").transform(table).select("features", "label")
    forest = RandomForestClassifier(numTrees=trees, maxDepth=depth, seed=7, featureSubsetStrategy="sqrt").fit(vectors)
    return Forest(tuple(t.toDebugString for t in forest.trees), known(words))


def findings_of(text: Column, forest: Forest) -> Column:
    """The candidates of a text with their votes: structs of place, value, votes."""

    def judged(words: Column, names: bool) -> Column:
        def candidate(word: Column, i: Column) -> Column:
            before = F.concat_ws(" ", F.get(words, i - 2), F.get(words, i - 1))
            likely = (F.length(word) >= SHORTEST) & (word.rlike(KEYLIKE) | word.rlike(LETTERS))
            if names:
                likely = likely | (F.length(word) >= 6) & (word.rlike(ASSIGNED) | awaited(before, word) | word.rlike(LOGIN))
            return F.when(likely, F.struct(i.alias("place"), value_of(word, before).alias("value"), before.alias("before"), word.alias("word")))

        return F.filter(F.transform(words, candidate), lambda x: x.isNotNull() & ((F.length(x["value"]) >= 6) | x["word"].rlike(LOGIN)))

    # Only a text with a credential name before = or :, or with an address, can hold what those patterns find word by word.
    may = text.rlike(NAMED + r"\s*[=:]") | text.contains("://")
    found = bound(words_of(text), lambda words: F.when(may, judged(words, True)).otherwise(judged(words, False)))
    scored = F.transform(found, lambda c: F.struct(c["place"].alias("place"), c["value"].alias("value"), features(c["value"], c["before"], c["word"], forest.words).alias("f")))

    def voted(c: Column) -> Column:
        total = sum((tree_column(t, c["f"]) for t in forest.trees), F.lit(0.0))
        return F.struct(c["place"].alias("place"), c["value"].alias("value"), (total / len(forest.trees)).alias("score"))

    return F.transform(scored, voted)


def scan(docs: DataFrame, forest: Forest | None = None) -> DataFrame:
    """One row per candidate: doc_id, place (word number from 0), n_chars, value_sha256, score, is_secret."""
    forest = forest or train(docs)
    found = docs.select("doc_id", F.explode(findings_of(text_or_empty(), forest)).alias("c"))
    return found.select(
        "doc_id",
        F.col("c.place").cast("long").alias("place"),
        F.length("c.value").cast("long").alias("n_chars"),
        F.sha2(F.col("c.value").cast("binary"), 256).alias("value_sha256"),
        F.col("c.score").alias("score"),
        (F.col("c.score") >= 0.5).alias("is_secret"),
    )


def masked(docs: DataFrame, forest: Forest | None = None) -> DataFrame:
    """The rows with every secret's value masked, with the columns that came; clean texts stay as they are."""
    forest = forest or train(docs)
    secrets = F.filter(findings_of(F.col("text"), forest), lambda c: c["score"] >= 0.5)
    text = bound(secrets, lambda found: F.when(F.size(found) == 0, F.col("text")).otherwise(F.aggregate(found, F.col("text"), lambda t, c: F.replace(t, c["value"], F.lit(MASK)))))
    return docs.withColumn("text", F.when(F.col("text").isNull(), None).otherwise(text))
