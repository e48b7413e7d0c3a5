"""Toxicity by a weighted finite-state pattern grammar.

Words become symbols: insult, threat verb, fate verb, modal, target, negation, report (verbs of speech) or other. Small
transducers rewrite a clause's symbols one after another and are composed into one machine. The threat transducer
matches patterns of several words (a threat verb and its target, stronger after a modal; a target, a modal and a
fate) and writes a match with its path weight; negation turns a near match into its denied form, reported speech turns
what follows it into its quoted form, and a target before it into its aimed form. A clause scores the weights of its
matches, by kind and form; a logistic model fitted on labelled rows weighs the forms.

An insult's weight is the log ratio of its shares in toxic and other texts. Words that mark toxic labels in the training
rows join the insults: those in at least SUPPORT toxic texts whose share there is RATIO times their share in the others.
Near copies of a text count once: texts are told apart by the least digest of their five-word shingles.
Training takes at most SAMPLE labelled rows (those of smallest hash), none of them held out: rows whose
crc32 of the id's decimal text is divisible by 5 never teach. labels, lang, source and doc_id are not
inputs of a score.

Defined cases: null and empty texts have no clause and score the model's base rate; texts are read
whole; repeated rows and null ids give one row each (a null id hashes as empty text); other columns are
ignored; without labels of both kinds the built-in weights are used; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from markerpanel.llm import textbytes as tb
from markerpanel.llm.common import arrow_map, discard, sliced, strings, table, written

#: Labelled rows that teach, at most.
SAMPLE = 20_000
#: Toxic texts of the sample, near copies once, that a word must stand in to join the lexicon, and its least ratio of shares.
SUPPORT, RATIO = 5, 20
SLICE = 1 << 20
SHINGLE = 5
#: Weight of an insult that no training row has, and the greatest that one can have.
KNOWN, HEAVIEST = 3.0, 6.0
#: The grammar's terminals.
INSULT = "idiot idiots moron morons stupid dumb loser losers scum trash garbage pathetic worthless disgusting clown clowns fool fools imbecile jerk filth vermin pig pigs ugly creep coward liar freak retard bastard bitch asshole dumbass scumbag".split(" ")
THREAT = "kill murder hurt destroy beat stab shoot burn hang strangle choke smash hunt".split(" ")
FATE = "die hang burn choke suffer bleed rot".split(" ")
MODAL = "will shall gonna going must should ll deserve deserves hope wish".split(" ")
TARGET = "you your yours yourself he she him her his they them their theirs those these this that".split(" ")
NEGATION = "not no never isnt arent wasnt werent dont doesnt didnt wont cannot cant nobody without".split(" ")
REPORT = "said says say told tells wrote writes quoted quote quotes called calls claimed claims reported reports alleged stated".split(" ")
OTHER, HIT, MENACE, AIM, DENY, SPEECH, VERB, DOOM, BOTH, MAY = range(10)
#: What a match can be rewritten to; the count and the weight of each are features, for insults and for threats.
FORMS = ("bare", "aimed", "denied", "quoted")
NEAR = 3


class Machine:
    """A deterministic transducer given by step(state, symbol) -> (state, symbol); state 0 begins a clause."""

    def __init__(self, step):
        self.step = step
        self.table: dict = {}

    def __call__(self, state, symbol):
        key = (state, symbol)
        if key not in self.table:
            self.table[key] = self.step(state, symbol)
        return self.table[key]

    def __or__(self, other: Machine) -> Machine:
        """Composition: what this one writes, the other reads. States are pairs, built when first met."""

        def step(state, symbol):
            a, b = state or (0, 0)
            a, symbol = self(a, symbol)
            b, symbol = other(b, symbol)
            return (a, b), symbol

        return Machine(step)


# A match is (HIT or MENACE, form, path weight).
def _threat(state, symbol):
    """state: words left in which a verb waits for its target, in which a modal and a target before still reach, and whether the verb followed a modal."""
    verb, modal, aim, strong = state or (0, 0, 0, 0)
    verb, modal, aim = max(0, verb - 1), max(0, modal - 1), max(0, aim - 1)
    if symbol == MAY:
        return (verb, NEAR + 1, aim, strong), OTHER
    if symbol in (DOOM, BOTH) and modal and aim:
        return (0, 0, 0, 0), (MENACE, "aimed", 2)
    if symbol in (VERB, BOTH):
        return (NEAR + 1, modal, aim, int(modal > 0)), OTHER
    if symbol == DOOM:
        return (verb, modal, aim, strong), OTHER
    if symbol == AIM:
        return (0, modal, NEAR + 1, 0), ((MENACE, "bare", 1 + strong) if verb else AIM)
    return (verb, modal, aim, strong), symbol


def _negation(state: int, symbol):
    """state: words left in which a negation still reaches."""
    if symbol == DENY:
        return NEAR + 1, symbol
    if isinstance(symbol, tuple) and state:
        return state - 1, (symbol[0], "denied", symbol[2])
    return max(0, state - 1), symbol


def _report(state: int, symbol):
    if symbol == SPEECH:
        return 1, symbol
    if isinstance(symbol, tuple) and state and symbol[1] in ("bare", "aimed"):
        return 1, (symbol[0], "quoted", symbol[2])
    return state, symbol


def _target(state: int, symbol):
    if symbol == AIM:
        return NEAR + 1, symbol
    if isinstance(symbol, tuple) and state and symbol[1] == "bare":
        return state - 1, (symbol[0], "aimed", symbol[2])
    return max(0, state - 1), symbol


def grammar() -> Machine:
    return Machine(_threat) | Machine(_negation) | Machine(_report) | Machine(_target)


FEATURES = tuple(f"{kind}_{form}" for kind in ("insult", "threat") for form in FORMS)
_CLAUSE_END = np.array([chr(b) in ".!?;:,\n|" for b in range(256)])
#: Symbols without which a clause has no match.
_STARTS = (HIT, VERB, DOOM, BOTH)


class Matcher:
    """lexicon: word -> (symbol, weight)."""

    def __init__(self, lexicon: dict[str, tuple[int, float]]):
        hashes = {}
        for word, entry in lexicon.items():
            raw = np.frombuffer(word.encode(), np.uint8)
            hashes[int(tb.span_hashes(raw, np.array([0]), np.array([len(raw)]))[0])] = entry
        self.keys = np.array(sorted(hashes), np.uint64)
        self.kinds = np.array([hashes[int(k)][0] for k in self.keys], np.int8)
        self.weights = np.array([hashes[int(k)][1] for k in self.keys])
        self.machine = grammar()

    def features(self, texts: pa.Array) -> np.ndarray:
        """Clauses' matches by kind and form, one row per text: their counts, then their weights."""
        out = np.zeros((len(texts), 2 * len(FEATURES)))
        data, offsets = tb.buffer(texts)
        low = tb.lowered(data)
        s, e, doc = tb.words(low, offsets, tb.ALPHANUMERIC)
        if not len(s) or not len(self.keys):
            return out
        h = tb.span_hashes(low, s, e)
        at = np.minimum(np.searchsorted(self.keys, h), len(self.keys) - 1)
        known = self.keys[at] == h
        kind = np.where(known, self.kinds[at], OTHER)
        weight = np.where(known, self.weights[at], 1.0)
        # a clause ends where an end mark or another text lies between two words
        ends = np.concatenate([[0], np.cumsum(_CLAUSE_END[data])])
        clause = np.concatenate([[0], np.cumsum((np.diff(ends[s]) > 0) | (np.diff(doc) > 0))])
        for c in np.unique(clause[np.isin(kind, _STARTS)]):
            lo, hi = np.searchsorted(clause, [c, c + 1])
            state = 0
            for symbol, own in zip(kind[lo:hi].tolist(), weight[lo:hi].tolist(), strict=True):
                state, wrote = self.machine(state, (HIT, "bare", 1) if symbol == HIT else symbol)
                if isinstance(wrote, tuple):
                    f = (wrote[0] == MENACE) * len(FORMS) + FORMS.index(wrote[1])
                    out[doc[lo], f] += 1
                    out[doc[lo], len(FEATURES) + f] += wrote[2] * (own if wrote[0] == HIT else KNOWN)
        return out


def shaped(x: np.ndarray) -> np.ndarray:
    """Model inputs: whether a form occurs, and what its matches weigh together (log)."""
    n = len(FEATURES)
    return np.hstack([np.ones((len(x), 1)), x[:, :n] > 0, np.log1p(x[:, n:])])


@dataclass
class Model:
    lexicon: dict[str, tuple[int, float]]
    weights: np.ndarray

    def matcher(self) -> Matcher:
        return Matcher(self.lexicon)

    def scores(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(shaped(x) @ self.weights, -30, 30)))


def built_in() -> dict[str, tuple[int, float]]:
    found = {w: (k, 1.0) for words, k in ((REPORT, SPEECH), (NEGATION, DENY), (TARGET, AIM), (MODAL, MAY)) for w in words}
    found |= {w: (BOTH if w in THREAT and w in FATE else VERB if w in THREAT else DOOM, 1.0) for w in THREAT + FATE}
    return found | {w: (HIT, KNOWN) for w in INSULT}


#: Without labels: a base rate below one half, denied and quoted forms weigh little.
PRIOR = np.array([-3.0, 1.0, 1.5, 0.0, 0.0, 1.0, 1.5, 0.0, 0.0, 1.8, 2.0, 0.2, 0.3, 1.2, 1.6, 0.1, 0.2])


def fit(x: np.ndarray, y: np.ndarray, pull: float = 1.0) -> np.ndarray:
    """Newton steps for logistic regression, drawn towards PRIOR, so that forms without examples keep it."""
    z, w = shaped(x), PRIOR.copy()
    penalty = np.full(len(w), pull)
    penalty[0] = 1e-3
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        grad = z.T @ (p - y) + penalty * (w - PRIOR)
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + np.diag(penalty), grad)
        w = w - np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-8:
            break
    return w


def held_out(key: str = "doc_id"):
    return F.crc32(F.coalesce(F.col(key).cast("string"), F.lit(""))) % 5 == 0


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Model:
    """Learn from at most ``sample`` labelled rows that aren't held out."""
    taught = labels.filter("toxic in (0, 1) and doc_id is not null").filter(~held_out()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    taught = taught.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    # a text that occurs often teaches once; the sample's ids are bounded, so they may be sent to every task
    rows = docs.select("doc_id", "text").join(F.broadcast(taught), "doc_id").filter("text is not null").groupBy(F.sha2("text", 256).alias("d")).agg(F.max("toxic").alias("toxic"), F.min("doc_id").alias("doc_id"))
    rows = written(docs.select("doc_id", "text").join(F.broadcast(rows.select("doc_id", "toxic")), "doc_id"))

    def about(words):
        """The words, and the least digest of their shingles: texts with the same one count as copies."""
        runs = F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.size(words) - SHINGLE + 1)), lambda k: F.md5(F.array_join(F.slice(words, k, F.lit(SHINGLE)), " ").cast("binary")))
        return F.struct(F.array_min(runs).alias("own"), F.array_distinct(words).alias("words"))

    split = F.split(F.lower("text"), r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    told = rows.select("toxic", F.transform(F.array(split), about)[0].alias("a")).select("toxic", "a.own", "a.words")
    words = told.select("toxic", "own", F.explode("words").alias("w")).filter("length(w) >= 3")
    sizes = {r.toxic: r.n for r in told.groupBy("toxic").agg(F.countDistinct("own").alias("n")).collect()}
    lexicon = built_in()
    if not sizes.get(0) or not sizes.get(1):
        return Model(lexicon, PRIOR)
    n1, n0 = sizes[1], sizes[0]
    counts = words.distinct().groupBy("w").agg(F.sum("toxic").alias("a"), F.count_if(F.col("toxic") == 0).alias("b")).filter(f"a >= {SUPPORT}")
    # the floor doesn't grow with the sample, so forms of one small language can pass too; the sample bounds the lexicon
    for r in counts.filter(f"(a + 0.5) / {n1} > {RATIO} * (b + 0.5) / {n0}").collect():
        if lexicon.get(r.w, (HIT, 0))[0] == HIT:
            lexicon[r.w] = (HIT, min(HEAVIEST, math.log((r.a + 0.5) / n1 * n0 / (r.b + 0.5))))
    model = Model(lexicon, PRIOR)
    held = docs.sparkSession.sparkContext.broadcast(model)
    seen = _features(rows.select(F.col("toxic").cast("long").alias("doc_id"), "text"), held).select("doc_id", "x").toLocalIterator()
    table_ = [(r.doc_id, r.x) for r in seen]
    discard(rows)
    return Model(lexicon, fit(np.array([x for _, x in table_]), np.array([float(t) for t, _ in table_])))


def _features(rows: DataFrame, held, scores: bool = False) -> DataFrame:
    kind = rows.schema["doc_id"].dataType.simpleString()

    def make():
        model = held.value
        matcher = model.matcher()

        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            col = strings(batch.column(1))
            for lo, hi in sliced(np.diff(np.frombuffer(col.buffers()[1], np.int64, len(col) + 1)), SLICE):
                x = matcher.features(col.slice(lo, hi - lo))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.array(model.scores(x)), pa.array(list(x), pa.list_(pa.float64()))], names=["doc_id", "score", "x"])

        return step

    return arrow_map(rows, make, f"doc_id {kind}, score double, x array<double>")


def scored(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """doc_id, held_out, score, predicted, and forms: the matched clauses' counts by name."""
    held = docs.sparkSession.sparkContext.broadcast(train(docs, labels, sample))
    out = _features(docs.select("doc_id", "text"), held)
    forms = F.map_from_arrays(F.array(*map(F.lit, FEATURES)), F.slice("x", 1, len(FEATURES)))
    return out.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), F.map_filter(forms, lambda k, v: v > 0).alias("forms"))


def op7(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return scored(docs, table(spark, sf_dir, "labels").select("doc_id", "toxic")).select("doc_id", "held_out", "score", "predicted")


def area(pairs: list[tuple[float, int]]) -> float:
    """Probability that a random positive scores above a random negative, ties half."""
    pos, neg = [s for s, t in pairs if t], [s for s, t in pairs if not t]
    order = sorted(neg)
    import bisect

    return sum(bisect.bisect_left(order, s) + (bisect.bisect_right(order, s) - bisect.bisect_left(order, s)) / 2 for s in pos) / max(1, len(pos) * len(neg)) if pos and neg else math.nan
