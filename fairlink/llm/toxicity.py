"""Toxicity by a weighted finite-state grammar over clauses.

Words become symbols: insult, threat, target, negation, report, other. Small transducers rewrite
or mark the symbols of a clause: negation turns an insult that follows it closely into a negated
one, reported speech turns insults after a reporting verb into quoted ones, the insult, target and threat
transducers put out what is matched. They are composed once into one machine by the usual
product of reachable states, and a clause is scored by one run. A document's score is a logistic
function of its counts of matches.

The insult lexicon and the weights are learned from labelled rows only. Lexicon: words and word
beginnings whose share of toxic texts could not come about by chance among all the terms, rare ones too, chosen
greedily until each toxic training text is covered several times; a fixed seed list is kept as far as
the labels do not speak against it. Weights: a logistic fit drawn to prior weights. Learning reads at most TRAIN_ROWS
labelled rows, the first ones by a hash of doc_id, each with one text (the least, should a doc_id repeat); rows with crc32(doc_id) mod 5 = 0 are never
read. Scoring reads every whole text in one pass without a shuffle; what is sent to the tasks is the lexicon, LEXICON terms at most.

Null and empty texts have no matches and get the score of that. Ties and repeated rows do not meet.
"""

from __future__ import annotations

import math
import re
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fairlink.llm.common import RowBuffer, durable, kept, slices

TRAIN_ROWS = 20_000
LEXICON = 4_000
TERMS_AT_ONCE = 200_000
FOLDS = 5
COVER = 4

# Fixed word lists: English, German, French, Spanish.
SEEDS = frozenset(
    "idiot moron stupid scum trash worthless disgusting clown loser pathetic imbecile dumb bastard asshole retard vermin "
    "trottel abschaum wertlos widerlich versager arschloch drecksack crétin débile ordure salaud connard abruti "
    "imbécil estúpido basura asqueroso inútil cabrón gilipollas".split()
)
THREATS = frozenset(
    "kill hurt destroy beat smash murder shoot stab hang burn töten umbringen vernichten schlagen erschießen "
    "tuer frapper détruire égorger matar golpear destruir degollar".split()
)
TARGETS = frozenset(
    "you your yours u they them their he him she her these those people du dich dir dein deine ihr euch sie ihnen tu toi te ton vous votre ils elles leur usted ustedes ti tú vosotros ellos ellas".split()
)
NEGATIONS = frozenset("not no never nobody isn't aren't wasn't don't doesn't didn't won't cannot nicht kein keine keinen nie niemals pas jamais aucun aucune no nunca jamás ningún ninguna tampoco".split())
REPORTS = frozenset(
    "said says say called calls wrote writes reported claimed claims quoted quote according told sagte sagt nannte schrieb behauptete zitat dit disait appelé écrit déclaré selon dijo dice llamó escribió según".split()
)

INSULT, THREAT, TARGET, NEGATED, QUOTED, NEGATION, REPORT, OTHER = "ihtjqnrx"
MATCHES = ("insult", "aimed", "negated", "quoted", "threat")
#: Prior weights of the matches, and of having none.
PRIOR = {"insult": 4.0, "aimed": 1.0, "negated": 0.5, "quoted": 0.8, "threat": 2.0}
PRIOR_BIAS = -3.0

_WORD = re.compile(r"[^\W\d_]+(?:['’][^\W\d_]+)?")
_CLAUSE = re.compile(r"[.,;:!?\n()\"“”„«»]|\b(?:and|but|und|aber|et|mais|y|pero)\b")


@dataclass
class Transducer:
    """Arcs (state, symbol) -> (state, outputs); a missing arc copies the symbol and stays."""

    arcs: dict = field(default_factory=dict)
    start: object = 0

    def step(self, state, symbol: str) -> tuple[object, tuple[str, ...]]:
        return self.arcs.get((state, symbol), (state, (symbol,)))


def negation(reach: int = 3) -> Transducer:
    """Insults within `reach` words after a negation come out as negated."""
    arcs = {}
    for left in range(reach + 1):
        arcs[left, NEGATION] = reach, (NEGATION,)
        for symbol in (INSULT, THREAT, TARGET, REPORT, OTHER):
            out = NEGATED if symbol == INSULT and left else OTHER if symbol == THREAT and left else symbol
            arcs[left, symbol] = max(0, left - 1), (out,)
    return Transducer(arcs)


def reported() -> Transducer:
    """Insults after a reporting verb of the clause come out as quoted."""
    arcs = {(0, REPORT): (1, (REPORT,)), (1, INSULT): (1, (QUOTED,)), (1, THREAT): (1, (OTHER,))}
    return Transducer(arcs)


def insults() -> Transducer:
    return Transducer({(0, INSULT): (0, (INSULT, "insult")), (0, NEGATED): (0, (NEGATED, "negated")), (0, QUOTED): (0, (QUOTED, "quoted"))})


def aimed(symbol: str, match: str) -> Transducer:
    """One match per clause that holds the symbol and a target, in either order."""
    seen, target, done = "seen", "target", "done"
    arcs = {(0, symbol): (seen, (symbol,)), (0, TARGET): (target, (TARGET,)), (seen, TARGET): (done, (TARGET, match)), (target, symbol): (done, (symbol, match))}
    return Transducer(arcs)


def compose(first: Transducer, second: Transducer, symbols: str = "ihtnrx") -> Transducer:
    """The machine that feeds the outputs of the first to the second, over reachable states."""
    arcs, todo, known = {}, [(first.start, second.start)], {(first.start, second.start)}
    while todo:
        state = todo.pop()
        for symbol in symbols:
            a, outputs = first.step(state[0], symbol)
            b, out = state[1], []
            for o in outputs:
                b, more = second.step(b, o)
                out.extend(more)
            arcs[state, symbol] = (a, b), tuple(out)
            if (a, b) not in known:
                known.add((a, b)), todo.append((a, b))
    return Transducer(arcs, (first.start, second.start))


def grammar() -> Transducer:
    machine = negation()
    for part in (reported(), insults(), aimed(INSULT, "aimed"), aimed(THREAT, "threat")):
        machine = compose(machine, part)
    return machine


@dataclass
class Lexicon:
    """Whole words, and beginnings of longer words."""

    words: frozenset
    stems: frozenset

    def holds(self, word: str) -> bool:
        return word in self.words or any(word[:k] in self.stems for k in range(3, min(len(word), 9)))


class Scorer:
    """Counts matches in texts."""

    def __init__(self, lexicon: Lexicon):
        import ahocorasick

        kept("toxicity", dict)
        self.lexicon, self.machine = lexicon, grammar()
        self.find = ahocorasick.Automaton()
        for term in lexicon.words | lexicon.stems | THREATS:
            self.find.add_word(term, len(term))
        self.find.make_automaton()

    def symbol(self, word: str) -> str:
        if self.lexicon.holds(word):
            return INSULT
        for words, symbol in ((THREATS, THREAT), (NEGATIONS, NEGATION), (REPORTS, REPORT), (TARGETS, TARGET)):
            if word in words:
                return symbol
        return NEGATION if word.endswith(("n't", "n’t")) else OTHER

    def clause(self, words: list[str]) -> Counter:
        state, out, step = self.machine.start, Counter(), self.machine.step
        for word in words:
            state, outputs = step(state, self.symbol(word))
            out.update(o for o in outputs if len(o) > 1)
        return out

    def counts(self, text: str) -> tuple[int, ...]:
        """How often each of MATCHES occurs. Clauses are read whole; the text is passed once."""
        lower = text.lower()
        total: Counter = Counter()
        done, begin, marks, mark = -1, 0, None, None
        for end, size in self.find.iter(lower):
            at = end - size + 1
            if at < done or at and lower[at - 1].isalpha():
                continue
            if marks is None:
                marks = _CLAUSE.finditer(lower)
                mark = next(marks, None)
            while mark and mark.end() <= at:
                begin, mark = mark.end(), next(marks, None)
            done = mark.start() if mark else len(lower)
            total += self.clause(_WORD.findall(lower, begin, done))
        return tuple(total[m] for m in MATCHES)


def terms(text: str) -> set[str]:
    """Words, and beginnings of four to eight letters marked by a star."""
    words = {w for w in _WORD.findall(text.lower()) if len(w) > 2}
    return words | {w[:k] + "*" for w in words for k in range(4, 9) if len(w) > k}


def significant(n_toxic: int, n_clean: int, tried: int) -> F.Column:
    """Whether chance would hardly give a term to n toxic texts beside `clean` others, were all the tried terms idle."""
    share = (n_toxic + 0.5) / (n_toxic + n_clean + 1)
    least = -math.log(max(1, tried) / 0.5)
    n, clean = F.col("n"), F.col("clean")
    q = n / (n + clean)
    # Upper bound of the log chance of so many hits.
    tail = F.when(q <= share, 0.0).otherwise(-(n * F.log(q / share) + F.when(clean > 0, clean * F.log((1 - q) / (1 - share))).otherwise(0.0)))
    return (n > 2) & (n >= 4 * clean) & (tail < least)


def choose(toxic: list[set[str]], clean: Counter) -> list[str]:
    """Of the significant terms that the toxic texts hold, a greedy cover of the texts."""
    holders = defaultdict(set)
    for i, doc in enumerate(toxic):
        for t in doc:
            holders[t].add(i)
    need = [COVER] * len(toxic)
    gain = {t: len(h) for t, h in holders.items()}
    chosen: list[str] = []
    while gain and len(chosen) < LEXICON:
        # Of terms that cover as much, the most specific: whole words, then longer beginnings.
        best = max(gain, key=lambda t: (gain[t], -clean[t], not t.endswith("*"), len(t), t))
        if gain.pop(best) <= 0:
            break
        chosen.append(best)
        root = best.rstrip("*")
        for t in [t for t in gain if (t.startswith(root) or root.startswith(t.rstrip("*"))) and holders[t] <= holders[best]]:
            del gain[t]
        for i in holders[best]:
            need[i] -= 1
            if need[i] == 0:
                for t in toxic[i]:
                    if t in gain:
                        gain[t] -= 1
    return chosen


def fit(counts: np.ndarray, label: np.ndarray, many: np.ndarray, pull: float = 1.0, steps: int = 60) -> np.ndarray:
    """Weights of log(1 + count) and the bias last, for rows that stand for `many` texts, by Newton steps of a logistic fit drawn to the prior."""
    x = np.c_[np.log1p(counts), np.ones(len(counts))]
    prior = np.array([*(PRIOR[m] for m in MATCHES), PRIOR_BIAS])
    w = prior.copy()
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        gradient = x.T @ (many * (label - p)) - pull * (w - prior)
        hessian = (x * (many * p * (1 - p))[:, None]).T @ x + pull * np.eye(len(w))
        move = np.linalg.solve(hessian, gradient)
        w = w + np.clip(move, -1, 1)
        if np.abs(move).max() < 1e-6:
            break
    w[: len(MATCHES)] = np.maximum(w[: len(MATCHES)], 0)
    return w


@dataclass
class Model:
    lexicon: Lexicon
    weights: np.ndarray

    def score(self, counts: np.ndarray) -> np.ndarray:
        x = np.c_[np.log1p(counts), np.ones(len(counts))]
        return 1 / (1 + np.exp(-np.clip(x @ self.weights, -30, 30)))


def held_out() -> F.Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % FOLDS == 0, F.lit(False))


def learn(docs: DataFrame, labels: DataFrame, rows: int = TRAIN_ROWS) -> Model:
    """The lexicon and the weights from at most `rows` labelled rows outside the held-out fold."""
    spark = docs.sparkSession
    own = labels.where("toxic IS NOT NULL AND doc_id IS NOT NULL").groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    sample = own.where(~held_out()).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows).collect()
    if not sample:
        return Model(Lexicon(SEEDS, frozenset()), np.array([*(PRIOR[m] for m in MATCHES), PRIOR_BIAS]))
    # TRAIN_ROWS pairs of numbers at most.
    small = F.broadcast(spark.createDataFrame(sample, "doc_id long, toxic int"))
    # One text a doc_id, so that the written table has at most `rows` texts.
    train = durable(docs.select("doc_id", "text").join(small, "doc_id").where("text IS NOT NULL").groupBy("doc_id").agg(F.min("text").alias("text"), F.min("toxic").alias("toxic")).select("text", "toxic"))

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept("toxicity", dict)  # what another operator left in the worker goes
        count: Counter = Counter()
        rows = lambda: pa.record_batch([pa.array(count.keys(), pa.string()), pa.array(count.values(), pa.int64())], names=["term", "n"])
        for (texts,) in slices(batches, "text"):
            for text in set(texts):
                count.update(terms(text))
                count[""] += 1
                if len(count) > TERMS_AT_ONCE:
                    yield rows()
                    count.clear()
        yield rows()

    per_term = lambda toxic: train.where(f"toxic = {toxic}").mapInArrow(counted, "term string, n long").groupBy("term").agg(F.sum("n").alias("n"))
    # Every term with its counts stays in Spark; the significant ones and the seeds come to the driver.
    both = durable(per_term(1).where("n > 2 OR term = ''").join(per_term(0).withColumnRenamed("n", "clean"), "term", "full").select("term", F.coalesce("n", F.lit(0)).alias("n"), F.coalesce("clean", F.lit(0)).alias("clean")))
    n_clean = both.where("term = ''").agg(F.sum("clean")).first()[0] or 0
    n_toxic, tried = train.where("toxic = 1").count(), both.where("n > 2 AND term <> ''").count()
    tests = significant(n_toxic, n_clean, tried + len(SEEDS))
    found = both.where("term <> ''").withColumn("good", tests).where(F.col("good") | F.col("term").isin(*SEEDS)).collect()
    hits, clean = Counter({r["term"]: r["n"] for r in found}), Counter({r["term"]: r["clean"] for r in found})
    good = {r["term"] for r in found if r["good"]}

    def held(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for (texts,) in slices(batches, "text"):
            rows = [sorted(terms(t) & good) for t in texts]
            yield pa.record_batch([pa.array(rows, pa.list_(pa.string()))], names=["terms"])

    toxic = [set(r["terms"]) for r in train.where("toxic = 1").mapInArrow(held, "terms array<string>").collect()]
    toxic.sort(key=sorted)
    chosen = choose(toxic, clean)
    held_on = {s for s in SEEDS if clean[s] < 3 or hits[s] >= clean[s]}
    lexicon = Lexicon(frozenset(held_on | {t for t in chosen if not t.endswith("*")}), frozenset(t[:-1] for t in chosen if t.endswith("*")))
    matched = _matches(train, lexicon, "toxic").groupBy("toxic", *MATCHES).agg(F.count("*").alias("n")).orderBy("toxic", *MATCHES).collect()
    counts = np.array([[r[m] for m in MATCHES] for r in matched], float).reshape(-1, len(MATCHES))
    return Model(lexicon, fit(counts, np.array([r["toxic"] for r in matched], float), np.array([r["n"] for r in matched], float)))


def _matches(docs: DataFrame, lexicon: Lexicon, key: str) -> DataFrame:
    kind = dict(docs.dtypes)[key]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(lexicon)
        out = RowBuffer(pa.schema([(key, pa.int64() if kind == "bigint" else pa.int32()), *((m, pa.int64()) for m in MATCHES)]))
        for keys, texts in slices(batches, key, "text"):
            for k, text in zip(keys, texts, strict=True):
                out.add((k, *scorer.counts(text or "")))
            if out.full():
                yield out.take()
        yield out.take()

    return docs.select(key, "text").mapInArrow(run, f"{key} {kind}, " + ", ".join(f"{m} long" for m in MATCHES))


def weighed(model: Model) -> F.Column:
    """The score of a row of match counts."""
    total = F.lit(float(model.weights[-1]))
    for m, w in zip(MATCHES, model.weights[:-1], strict=True):
        total = total + F.lit(float(w)) * F.log1p(F.col(m).cast("double"))
    return 1 / (1 + F.exp(-total))


def score(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted and the counts of matches of every row."""
    model = learn(docs, labels)
    scored = _matches(docs, model.lexicon, "doc_id").withColumn("score", weighed(model))
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), *MATCHES)


def without_toxic(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows that are not predicted toxic, with the columns that came."""
    model = learn(docs, labels)
    schema = docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(model.lexicon)
        for batch in batches:
            texts = batch.column(batch.schema.get_field_index("text")).to_pylist()
            keep = model.score(np.array([scorer.counts(t or "") for t in texts], float).reshape(-1, len(MATCHES))) < 0.5
            yield batch.filter(pa.array(keep))

    return docs.mapInArrow(run, schema)
