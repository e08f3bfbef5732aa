"""Toxicity by a weighted grammar of finite-state transducers.

Words become symbols (insult, threat, target, negation, report, other); small
transducers rewrite the symbols of a clause one after another: negation weakens the insults and
threats that soon follow it, reported speech marks what is quoted, a target in the
clause, before or after, makes what is aimed at it direct. They are composed into one machine whose
last part gives weights, which count by the strength of the word they are for. Clauses are scored, not words: a document's features are the
sum and the largest of its clauses' weights and how many clauses matched, and a logistic function
turns them into a score. A clause in which all that is found is negated does not match. Clauses are read to their ends, however long.

Which words are insults, beyond a fixed list, and the logistic function are learned from a
bounded sample of labelled documents (``MOST``), whole texts.

Defined results: a null or empty text has no clauses and scores as all texts without a
match; without labels of both classes, fixed words and weights apply; repeated rows
score alike; an empty table gives no rows; labels, lang, source and doc_id enter no
score; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.ship import map_arrow
from .labelled import remainder, sample, shares
from .textbatch import Words, slices, words

MOST, MODULUS, HELD_OUT, PREDICTED_FROM = 6000, 5, 0, 0.5
#: A word is learned as an insult if the lower bound of its log odds ratio (ERRORS standard errors) is over this, at most so many words.
LEAST_ODDS, ERRORS, MOST_WORDS = 1.6, 2.5, 200
#: Lengths of beginnings of words that may be learned too, longest first.
STEMS = (8, 7, 6, 5, 4)
#: Words after a negation that it reaches.
REACH = 3

#: Word lists.
INSULTS = "idiot moron stupid trash scum loser pathetic worthless disgusting clown dumb fool jerk garbage imbecile coward filth creep vermin cretin".split()
THREATS = (
    "kill hurt destroy burn crush beat shoot stab attack hunt "
    "töten umbringen erschießen verbrennen zerstören verprügeln erstechen "
    "tuer frapper détruire brûler abattre poignarder écraser "
    "matar golpear destruir quemar disparar apuñalar aplastar"
).split()
TARGETS = (
    "you u your yours you're he she they them him her his their those these "
    "du dich dir dein deine ihr euch euer ihn ihm sie "
    "tu te toi ton ta tes vous votre vos lui eux "
    "tú tu ti usted ustedes vosotros ellos ellas él ella"
).split()
NEGATIONS = (
    "not never no don't isn't aren't wasn't won't can't without nobody "
    "nicht nie niemals kein keine keiner ohne niemand "
    "pas jamais aucun aucune sans ni personne "
    "nunca jamás ningún ninguna sin nadie tampoco"
).split()
REPORTS = (
    "said says say wrote writes called calls quoted quotes claimed claims reported told according "
    "sagte sagt schrieb schreibt nannte nennt behauptete behauptet zitierte laut berichtete "
    "dit disait écrit écrivait appelle appelait affirme affirmait selon rapporte "
    "dijo dice escribió escribe llamó llama afirmó afirma según citó"
).split()

OTHER, INSULT, THREAT, TARGET, NEGATION, REPORT = range(6)
#: Symbols that rewriting adds: weakened, quoted, and aimed versions; the late ones are written at a target that comes after its insult or threat.
WEAK, QUOTED, AIMED, MENACE, LATE_AIMED, LATE_MENACE = range(6, 12)
SYMBOLS = 12
ENDS = ".;:!?"
_TRIM = ".,;:!?\"'()[]|#*$%&<>"


@dataclass
class Transducer:
    """A deterministic machine: at a state and a symbol, the next state, the symbol written and a weight. What is not listed keeps state and symbol."""

    states: int
    arcs: dict[tuple[int, int], tuple[int, int, float]] = field(default_factory=dict)

    def step(self, state: int, symbol: int) -> tuple[int, int, float]:
        return self.arcs.get((state, symbol), (state, symbol, 0.0))

    def then(self, other: Transducer) -> Transducer:
        """The composition: ``other`` reads what this one writes; weights add up."""
        arcs = {}
        for a in range(self.states):
            for b in range(other.states):
                for symbol in range(SYMBOLS):
                    a2, middle, w1 = self.step(a, symbol)
                    b2, out, w2 = other.step(b, middle)
                    arcs[a * other.states + b, symbol] = (a2 * other.states + b2, out, w1 + w2)
        return Transducer(self.states * other.states, arcs)


def negation() -> Transducer:
    """An insult or a threat up to REACH words after a negation is weak."""
    arcs = {(s, NEGATION): (REACH, NEGATION, 0.0) for s in range(REACH + 1)}
    for s in range(1, REACH + 1):
        arcs |= {(s, x): (s - 1, x, 0.0) for x in (OTHER, TARGET, REPORT)}
        arcs |= {(s, x): (s - 1, WEAK, 0.0) for x in (INSULT, THREAT)}
    return Transducer(REACH + 1, arcs)


def reported() -> Transducer:
    """After a verb of saying, what follows in the clause is quoted."""
    arcs = {(s, REPORT): (1, REPORT, 0.0) for s in range(2)}
    return Transducer(2, arcs | {(1, x): (1, QUOTED, 0.0) for x in (INSULT, THREAT)})


def aimed() -> Transducer:
    """Insults and threats with a target in the clause, before or after them, are direct; states: nothing, target seen, insult seen, threat seen."""
    arcs = {(0, TARGET): (1, TARGET, 0.0), (0, INSULT): (2, INSULT, 0.0), (0, THREAT): (3, THREAT, 0.0)}
    arcs |= {(1, INSULT): (1, AIMED, 0.0), (1, THREAT): (1, MENACE, 0.0)}
    arcs |= {(2, THREAT): (3, THREAT, 0.0), (3, INSULT): (2, INSULT, 0.0)}
    arcs |= {(2, TARGET): (1, LATE_AIMED, 0.0), (3, TARGET): (1, LATE_MENACE, 0.0)}
    return Transducer(4, arcs)


def weighing() -> Transducer:
    """The weight of each symbol; a late one's is what the word gains, which was read without a target."""
    weights = {INSULT: 1.0, THREAT: 0.6, WEAK: 0.3, QUOTED: 0.5, AIMED: 1.7, MENACE: 2.0, LATE_AIMED: 0.7, LATE_MENACE: 1.4}
    return Transducer(1, {(0, x): (0, x, w) for x, w in weights.items()})


GRAMMAR = negation().then(reported()).then(aimed()).then(weighing())
#: For comparison: the same weights without any rewriting, so that words count wherever they stand.
WORDS_ALONE = weighing()
#: What makes a clause match: anything but weakened words.
MATCHES = (INSULT, THREAT, QUOTED, AIMED, MENACE)


def read_clause(symbols: list[int], strengths: list[float], grammar: Transducer = GRAMMAR) -> tuple[float, bool]:
    """The weight of one clause and whether it matches; weights count by the strength of the insult or threat they are for."""
    state, total, matches, pending = 0, 0.0, False, 1.0
    for symbol, strength in zip(symbols, strengths, strict=True):
        state, written, weight = grammar.step(state, symbol)
        if weight:
            total += weight * (pending if written in (LATE_AIMED, LATE_MENACE) else strength)
        if written in (INSULT, THREAT):
            pending = strength
        matches |= written in MATCHES
    return total, matches


def clause_weight(symbols: list[int], strengths: list[float], grammar: Transducer = GRAMMAR) -> float:
    return read_clause(symbols, strengths, grammar)[0]


def plain(word: str) -> str:
    return word.strip(_TRIM).lower()


def with_stems(word: str) -> list[str]:
    """A word and its beginnings, which are marked by a star: insults of inflecting or compounding languages share them."""
    return [word, *(f"{word[:k]}*" for k in STEMS if len(word) > k)]


def looked_up(word: str, table: dict[str, tuple[int, float]]) -> tuple[int, float]:
    """The entry of the word, or else of its longest listed beginning."""
    found = table.get(word)
    if found is None:
        for k in STEMS:
            if len(word) > k and (found := table.get(f"{word[:k]}*")):
                break
    return found or (OTHER, 0.0)


def lexicon(learned: dict[str, float]) -> dict[str, tuple[int, float]]:
    """Symbol and strength of every listed word; learned insults go before fixed lists."""
    table = {w: (INSULT, 1.0) for w in INSULTS}
    for kind, own in ((THREAT, THREATS), (TARGET, TARGETS), (NEGATION, NEGATIONS), (REPORT, REPORTS)):
        table |= {w: (kind, 1.0) for w in own}
    return table | {w: (INSULT, s) for w, s in learned.items()}


def features(split: Words, table: dict[str, tuple[int, float]], grammar: Transducer = GRAMMAR) -> np.ndarray:
    """For each text: whether a clause matched, log of 1 + the sum, the largest weight, log of 1 + matching clauses, log of 1 + the sum for 100 words."""
    rows = len(split.bounds) - 1
    out = np.zeros((rows, 5))
    vocabulary = split.vocabulary.to_pylist()
    known = [looked_up(plain(w), table) for w in vocabulary]
    symbol = np.array([k for k, _ in known], dtype=np.int64)[split.codes]
    hot = np.flatnonzero((symbol == INSULT) | (symbol == THREAT))
    if not len(hot):
        return out
    closes = np.array([w[-1:] in ENDS for w in vocabulary], dtype=bool)[split.codes]
    # A clause ends at a word that closes it and at the end of its text.
    ends = np.union1d(np.flatnonzero(closes), (split.bounds[1:] - 1)[split.counts > 0])
    strength = np.array([s for _, s in known])[split.codes]
    telling = np.flatnonzero(symbol != OTHER)
    owners = split.owners
    sums: dict[int, list[float]] = {}
    matched = np.zeros(rows, dtype=np.int64)
    for clause in np.unique(np.searchsorted(ends, hot)).tolist():
        first, last = (int(ends[clause - 1]) + 1 if clause else 0), int(ends[clause])
        at = telling[np.searchsorted(telling, first) : np.searchsorted(telling, last, side="right")]
        # Only as many other words in between matter as a negation reaches.
        gaps = np.minimum(np.diff(at, prepend=at[0] - 1) - 1, REACH)
        places = np.cumsum(gaps + 1) - 1
        symbols, strengths = np.full(int(places[-1]) + 1, OTHER), np.zeros(int(places[-1]) + 1)
        symbols[places], strengths[places] = symbol[at], strength[at]
        weight, matches = read_clause(symbols.tolist(), strengths.tolist(), grammar)
        row = int(owners[first])
        sums.setdefault(row, []).append(weight)
        matched[row] += matches
    for row, weights in sums.items():
        out[row] = matched[row] > 0, np.log1p(sum(weights)), max(weights), np.log1p(matched[row]), np.log1p(100 * sum(weights) / split.counts[row])
    return out


def shingle_key(codes: np.ndarray, hashes: np.ndarray) -> int:
    """The least hash of three-word runs of a text: copies and most near copies share it, other texts do not."""
    h = hashes[codes]
    if len(h) < 3:
        return int(h.sum()) if len(h) else -1
    run = (h[:-2] * np.uint64(0x9E3779B97F4A7C15) ^ h[1:-1]) * np.uint64(0xD6E8FEB86659FD93) ^ h[2:]
    run = (run ^ (run >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return int((run >> np.uint64(1)).min())


def learned_insults(texts: list[tuple[set[str], int]]) -> dict[str, float]:
    """Words that tell toxic documents, one after another: the best by its lower bound, then the best over documents without it, and so on."""
    frequent = Counter(w for own, y in texts if y for w in own)
    names: dict[str, int] = {}
    docs = [np.array([names.setdefault(w, len(names)) for w in sorted(own) if frequent[w] > 2], dtype=np.int64) for own, _ in texts]
    label = np.array([y for _, y in texts], dtype=np.int64)
    if len(np.unique(label)) < 2 or not names:
        return {}
    word, doc = np.concatenate(docs), np.repeat(np.arange(len(docs)), [len(d) for d in docs])
    by_name = list(names)
    live = np.ones(len(docs), dtype=bool)
    out: dict[str, float] = {}
    for _ in range(MOST_WORDS):
        on = live[doc]
        bad, good = (np.bincount(word[on & (label[doc] == y)], minlength=len(names)) + 0.5 for y in (1, 0))
        all_bad, all_good = (live & (label == 1)).sum() + 1, (live & (label == 0)).sum() + 1
        bound = np.log(bad / good) - np.log(all_bad / all_good) - ERRORS * np.sqrt(1 / bad + 1 / good)
        best = int(bound.argmax())
        if bound[best] < LEAST_ODDS:
            break
        out[by_name[best]] = float(np.clip(bound[best] / 3, 0.3, 1.5))
        live[doc[word == best]] = False
    return out


def logistic(x: np.ndarray, y: np.ndarray, share: float) -> np.ndarray:
    """Coefficients and offset of a logistic regression in which class 1 has this share; a ridge keeps them finite."""
    weight = np.where(y == 1, share / max(1, (y == 1).sum()), (1 - share) / max(1, (y == 0).sum())) * len(y)
    full = np.column_stack([x, np.ones(len(x))])
    beta = np.zeros(full.shape[1])
    ridge = np.diag([*np.full(x.shape[1], 1.0), 1e-6])
    for _ in range(40):
        p = 1 / (1 + np.exp(-np.clip(full @ beta, -30, 30)))
        grad = full.T @ (weight * (p - y)) + ridge @ beta
        hess = (full * (weight * p * (1 - p))[:, None]).T @ full + ridge
        beta -= np.clip(np.linalg.solve(hess, grad), -3, 3)
    return beta


#: Without labels: a matching clause says toxic.
UNTRAINED = np.array([1.0, 1.0, 0.5, 0.5, 0.0, -2.0])


def train(docs: DataFrame, labels: DataFrame, most: int = MOST) -> tuple[dict[str, float], np.ndarray]:
    """Learned insults with their strengths, and the logistic function; one task reads the bounded sample."""
    share = shares(labels, "toxic", MODULUS, HELD_OUT)
    rows = sample(docs, labels, "toxic", MODULUS, HELD_OUT, most)

    def fit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        splits, y, ids, bags, keys = [], [], [], [], []
        for whole in batches:
            for batch in slices(whole):
                split = words(batch.column("text"))
                vocabulary = split.vocabulary.to_pylist()
                low = [plain(w) for w in vocabulary]
                hashes = np.array([zlib.crc32(w.encode()) for w in vocabulary], dtype=np.uint64)
                keys += [shingle_key(split.codes[a:b], hashes) for a, b in zip(split.bounds[:-1], split.bounds[1:], strict=True)]
                own = [[] if not w else with_stems(w) for w in low]
                bags += [{x for c in np.unique(split.codes[a:b]).tolist() for x in own[c]} for a, b in zip(split.bounds[:-1], split.bounds[1:], strict=True)]
                splits.append(split)
                y += batch.column("y").to_pylist()
                ids += batch.column("doc_id").to_pylist()
        order = np.lexsort((np.array(keys, dtype=np.int64), np.array([len(b) for b in bags]), np.array(ids, dtype=np.int64)))  # rows of one doc_id by their texts
        first = {keys[i]: i for i in order[::-1]}  # words are learned from one text of each group of copies, whose labels go together
        new = learned_insults([(bags[i], y[i]) for i in sorted(first.values())])
        beta = UNTRAINED
        if len(set(y)) == 2:
            x = np.concatenate([features(s, lexicon(new)) for s in splits])
            beta = logistic(x[order], np.array(y)[order], share)
        yield pa.RecordBatch.from_arrays([pa.array([list(new)], pa.list_(pa.string())), pa.array([list(new.values())], pa.list_(pa.float64())), pa.array([beta.tolist()], pa.list_(pa.float64()))], names=["words", "strengths", "beta"])

    (model,) = map_arrow(rows.select("doc_id", "text", F.col("y").cast("int").alias("y")).repartition(1), fit, "words array<string>, strengths array<double>, beta array<double>").collect() or [None]
    if model is None:
        return {}, UNTRAINED
    return dict(zip(model["words"], model["strengths"], strict=True)), np.array(model["beta"])


def scored(docs: DataFrame, model: tuple[dict[str, float], np.ndarray]) -> DataFrame:
    """(doc_id, score, clause_sum) of every document."""
    table, beta = lexicon(model[0]), model[1]

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in slices(whole):
                x = features(words(batch.column("text")), table)
                odds = np.clip(x @ beta[:-1] + beta[-1], -30, 30)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(1 / (1 + np.exp(-odds))), pa.array(np.expm1(x[:, 1]))], names=["doc_id", "score", "clause_sum"])

    return map_arrow(docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text")), score, "doc_id bigint, score double, clause_sum double")


def classify(docs: DataFrame, labels: DataFrame, most: int = MOST) -> DataFrame:
    """(doc_id, held_out, score, predicted, clause_sum) of every document."""
    out = scored(docs, train(docs, labels, most))
    return out.select("doc_id", F.coalesce(remainder(MODULUS) == HELD_OUT, F.lit(False)).alias("held_out"), "score", (F.col("score") >= PREDICTED_FROM).cast("int").alias("predicted"), "clause_sum")
