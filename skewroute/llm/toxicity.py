"""Toxicity by a learnt lexicon, a Levenshtein automaton over its trie, and context windows.

The lexicon is learnt from a bounded sample of labelled texts: words and stems that toxic texts hold and clean ones
do not. Its trie is intersected with the Levenshtein automaton of distance one: a state is the set of trie nodes that
the letters read so far may have reached, with the edits spent, and states are made deterministic as texts ask for
them. So a word costs one look-up a letter however large the lexicon, and misspelled terms are met like exact ones.
Each hit is weighed in its window: quotation marks around it and words that report speech lower it, words that address
the reader raise it. A logistic fit on the weighed sums gives the score.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from skewroute.llm.common import materialize, read_table, tidy, words_of

#: Labelled rows that the lexicon and the fit are learnt from, chosen by a hash of the id.
SAMPLE_ROWS = 12_000
#: Terms that a lexicon may hold; the most telling stay.
LEXICON_TERMS = 5_000
MIN_SUPPORT = 3
MIN_PRECISION = 0.8
MIN_STEMS = 2_000
STEM = (3, 12)
#: Shorter terms must be met exactly.
FUZZY_LENGTH = 5
WINDOW = 8
_MEMO_WORDS = 600_000
_STATES = 200_000

# Marks of quotation, words that report speech, words that address the reader.
QUOTES = "\"“”„«»‘’‹›"
REPORTING = frozenset("said says say wrote writes quoted quote quotes called calls word term phrase insult slur reported reportedly sagte schrieb zitat wort nannte dit écrit cité mot appelé dijo escribió cita palabra llamó".split())
ADDRESSING = frozenset("you your you're youre u ur du dich dir euch ihr tu te toi vous tes usted ustedes eres".split())


def normal(word: bytes) -> str:
    """Lower case without what is neither letter nor digit at either end."""
    text = word.decode("utf-8", "replace").lower()
    low, high = 0, len(text)
    while low < high and not text[low].isalnum():
        low += 1
    while high > low and not text[high - 1].isalnum():
        high -= 1
    return text[low:high]


@dataclass
class Term:
    text: str
    weight: float
    stem: bool  # met at the start of a longer word too


@dataclass
class Hit:
    term: int
    edits: int


class LexiconAutomaton:
    """Lazily determinised intersection of the lexicon's trie with the Levenshtein automaton of distance ``edits``."""

    def __init__(self, terms: list[Term], edits: int = 1):
        self.terms, self.edits = terms, edits
        self.children: list[dict[str, int]] = [{}]
        self.ends: list[int] = [-1]
        for n, t in enumerate(terms):
            at = 0
            for c in t.text:
                if c not in self.children[at]:
                    self.children[at][c] = len(self.children)
                    self.children.append({})
                    self.ends.append(-1)
                at = self.children[at][c]
            self.ends[at] = n
        self._reset()

    def _reset(self) -> None:
        self.moves: list[dict[str, int]] = []
        self.sets: list[tuple[tuple[int, int], ...]] = []
        self.whole: list[Hit | None] = []
        self.early: list[Hit | None] = []
        self.known: dict[tuple, int] = {}
        self.start = self._state({0: 0})

    def _state(self, nodes: dict[int, int]) -> int:
        todo = list(nodes.items())
        while todo:  # letters of the term that the word leaves out
            node, spent = todo.pop()
            if spent < self.edits:
                for child in self.children[node].values():
                    if nodes.get(child, self.edits + 1) > spent + 1:
                        nodes[child] = spent + 1
                        todo.append((child, spent + 1))
        key = tuple(sorted(nodes.items()))
        if key not in self.known:
            self.known[key] = len(self.sets)
            self.sets.append(key)
            self.moves.append({})
            found = [(spent, self.ends[node]) for node, spent in key if self.ends[node] >= 0 and (not spent or len(self.terms[self.ends[node]].text) >= FUZZY_LENGTH)]
            self.whole.append(Hit(min(found)[1], min(found)[0]) if found else None)
            stems = [x for x in found if self.terms[x[1]].stem]
            self.early.append(Hit(min(stems)[1], min(stems)[0]) if stems else None)
        return self.known[key]

    def _move(self, state: int, c: str) -> int:
        nodes: dict[int, int] = {}

        def reach(node: int, spent: int) -> None:
            if spent <= self.edits and nodes.get(node, self.edits + 1) > spent:
                nodes[node] = spent

        for node, spent in self.sets[state]:
            reach(node, spent + 1)
            for letter, child in self.children[node].items():
                reach(child, spent + (letter != c))
        self.moves[state][c] = to = self._state(nodes) if nodes else -1
        return to

    def find(self, word: str) -> Hit | None:
        """The hit of fewest edits, a whole word before a stem; None if no term is near."""
        if len(self.sets) > _STATES:
            self._reset()
        at, best = self.start, None
        for c in word:
            to = self.moves[at].get(c)
            at = self._move(at, c) if to is None else to
            if at < 0:
                return best
            if (stem := self.early[at]) and (best is None or stem.edits < best.edits):
                best = stem
        end = self.whole[at]
        return end if end and (best is None or end.edits <= best.edits) else best


@dataclass
class ToxicityModel:
    terms: list[Term]
    coefficients: np.ndarray = field(default_factory=lambda: np.zeros(FEATURES))
    center: np.ndarray = field(default_factory=lambda: np.zeros(FEATURES - 1))
    scale: np.ndarray = field(default_factory=lambda: np.ones(FEATURES - 1))

    def probability(self, x: np.ndarray) -> np.ndarray:
        z = ((x - self.center) / self.scale) @ self.coefficients[1:] + self.coefficients[0]
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


#: Intercept; exact words, stems, misspelled words, misspelled stems, the strongest hit, hits that are quoted.
FEATURES = 7


class Scorer:
    """Features of whole texts; keeps a bounded memo of words."""

    def __init__(self, terms: list[Term]):
        self.automaton, self.terms, self.memo = LexiconAutomaton(terms), terms, {}

    def _learn(self, words: list[bytes]) -> None:
        new = [w for w in set(words) if w not in self.memo]
        if len(self.memo) + len(new) > _MEMO_WORDS:
            self.memo.clear()
            new = list(set(words))
        find = self.automaton.find
        for w in new:
            self.memo[w] = find(normal(w))

    def window(self, words: list[bytes], i: int) -> tuple[float, float]:
        """How far the window speaks for quotation (0 to 1) and for addressing the reader (0 or 1)."""
        before = [w.decode("utf-8", "replace") for w in words[max(0, i - WINDOW) : i + 1]]
        after = [w.decode("utf-8", "replace") for w in words[i : i + 1 + WINDOW]]
        opened = any(w[:1] in QUOTES or w[:2].lstrip("([")[:1] in QUOTES for w in before if w)
        closed = any(w.rstrip(".,;:!?)]")[-1:] in QUOTES for w in after if w.rstrip(".,;:!?)]"))
        near = {w.lower().strip(QUOTES + ".,;:!?()[]") for w in (*before[:-1], *after[1:])}
        return 0.6 * (opened and closed) + 0.4 * bool(near & REPORTING), float(bool(near & ADDRESSING))

    def features(self, text: str | None) -> list[float]:
        words = words_of(text)
        self._learn(words)
        get = self.memo.__getitem__
        sums, top, quoted = [0.0] * 4, 0.0, 0.0
        for i, hit in enumerate(map(get, words)):
            if hit is None:
                continue
            term = self.terms[hit.term]
            quote, address = self.window(words, i)
            value = term.weight * (1 - 0.8 * quote) * (1 + 0.25 * address)
            sums[2 * (hit.edits > 0) + term.stem] += value
            top = max(top, value / (1 + hit.edits))
            quoted += quote >= 0.6
        return [*(math.log1p(s) for s in sums), top, math.log1p(quoted)]


def labelled_sample(docs: DataFrame, labels: DataFrame, rows: int) -> DataFrame:
    """``(text, toxic)`` of at most ``rows`` labelled documents whose id is not held out, one row for each text."""
    usable = labels.where(F.col("toxic").isNotNull() & ~held_out(F.col("doc_id")))
    picked = usable.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    # Bounded by ``rows``, hence broadcast: the documents are not shuffled.
    return docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id").where("text IS NOT NULL").dropDuplicates(["text"]).select("text", "toxic")


def held_out(doc_id):
    return F.crc32(doc_id.cast("string")) % 5 == 0


def _stem_counts(rows: DataFrame, among: set[str] | None) -> dict[str, tuple[int, int, int]]:
    """Documents, occurrences, and whole-word occurrences of each word start in the sample."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            docs, seen, whole = Counter(), Counter(), Counter()
            for text in b.column("text").to_pylist():
                words = Counter(normal(w) for w in words_of(text))
                stems: Counter = Counter()
                for w, n in words.items():
                    for k in range(STEM[0], min(STEM[1], len(w)) + 1):
                        if among is None or w[:k] in among:
                            stems[w[:k]] += n
                            if k == len(w):
                                whole[w] += n
                docs.update(stems.keys())
                seen.update(stems)
            if docs:
                keys = list(docs)
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), *(pa.array([c[k] for k in keys], pa.int64()) for c in (docs, seen, whole))], ["stem", "n", "seen", "whole"])

    counted = rows.select("text").mapInArrow(run, "stem string, n long, seen long, whole long").groupBy("stem").agg(F.sum("n").alias("n"), F.sum("seen").alias("seen"), F.sum("whole").alias("whole"))
    return {r["stem"]: (r["n"], r["seen"], r["whole"]) for r in counted.where(F.col("n") >= (MIN_SUPPORT if among is None else 1)).collect()}


def choose_terms(toxic: dict[str, tuple[int, int, int]], clean: dict[str, tuple[int, int, int]], n_toxic: int, n_clean: int) -> list[Term]:
    """The widest stems that tell toxic texts, each as long as it can be without losing texts.

    A stem splits into its continuations if three of them make up nearly all of its occurrences.
    """
    base = n_toxic / max(1, n_toxic + n_clean)
    # The more stems are tried, the more evidence each must show (log-likelihood ratio against chance).
    evidence = 2 * math.log(max(MIN_STEMS, len(toxic))) + 4

    def tells(stem: str) -> bool:
        a, b = toxic[stem][0], clean.get(stem, (0,))[0]
        share = (a + 0.5) / (a + b + 1)
        gain = 2 * (a * math.log(a / ((a + b) * base)) + (b * math.log(b / ((a + b) * (1 - base))) if b else 0)) if a / (a + b) > base else 0
        return share >= MIN_PRECISION and gain >= evidence

    good = {s for s in toxic if tells(s)}
    longer: dict[str, list[str]] = {}
    for s in good:
        longer.setdefault(s[:-1], []).append(s)
    chosen: list[str] = []
    todo = [s for s in good if s[:-1] not in good]
    while todo:
        stem = todo.pop()
        parts = sorted(longer.get(stem, ()), key=lambda s: -toxic[s][1])[:3]
        if parts and sum(toxic[s][1] for s in parts) >= 0.9 * toxic[stem][1]:
            todo += parts
        else:
            chosen.append(stem)
    weight = {s: math.log((toxic[s][0] + 0.5) / (n_toxic + 1)) - math.log((clean.get(s, (0,))[0] + 0.5) / (n_clean + 1)) for s in chosen}
    best = sorted(chosen, key=lambda s: (-toxic[s][0] * weight[s], s))[:LEXICON_TERMS]
    return [Term(s, weight[s], toxic[s][2] < 0.9 * toxic[s][1]) for s in sorted(best)]


def fit_logistic(x: np.ndarray, y: np.ndarray, penalty: float = 0.05, rounds: int = 40) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Coefficients (intercept first) by Newton steps on standardised columns, with their means and scales."""
    center, scale = x.mean(axis=0), np.maximum(x.std(axis=0), 1e-6)
    z = np.c_[np.ones(len(x)), (x - center) / scale]
    beta, ridge = np.zeros(z.shape[1]), np.r_[1e-6, np.full(x.shape[1], penalty)]
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ beta, -30, 30)))
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + np.diag(ridge + 1e-9), z.T @ (y - p) - ridge * beta)
        beta = beta + step
        if np.abs(step).max() < 1e-8:
            break
    return beta, center, scale


def train(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS) -> ToxicityModel:
    """Learn lexicon and fit. What reaches the driver is bounded by ``sample_rows``: counts of stems, feature rows."""
    sample = materialize(labelled_sample(docs, labels, sample_rows), "sample")
    sizes = {r["toxic"]: r["n"] for r in sample.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    n_toxic, n_clean = sizes.get(1, 0), sizes.get(0, 0)
    if not n_toxic or not n_clean:
        model = ToxicityModel([])
        model.coefficients[0] = -5.0 if not n_toxic else 5.0
        return model
    toxic = _stem_counts(sample.where("toxic = 1"), None)
    clean = _stem_counts(sample.where("toxic = 0"), set(toxic))
    terms = choose_terms(toxic, clean, n_toxic, n_clean)
    rows = _features(sample.select("toxic", "text"), terms).toPandas()
    x = np.array(rows["x"].tolist(), np.float64)
    return ToxicityModel(terms, *fit_logistic(x, rows["toxic"].to_numpy(np.float64)))


def _features(rows: DataFrame, terms: list[Term]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(terms)
        for b in batches:
            x = [scorer.features(t) for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("toxic").cast(pa.int64()), pa.array(x, pa.list_(pa.float64()))], ["toxic", "x"])

    return rows.select(F.col("toxic").cast("long").alias("toxic"), "text").mapInArrow(run, "toxic long, x array<double>")


def score(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, score)`` of every row: its whole text alone decides. Null texts score as empty ones.

    Repeated rows give repeated rows; an empty table gives an empty table; other columns are not read.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(shared.value.terms)
        for b in batches:
            x = np.array([scorer.features(t) for t in b.column("t").to_pylist()], np.float64).reshape(-1, FEATURES - 1)
            yield pa.RecordBatch.from_arrays([b.column("i"), pa.array(shared.value.probability(x))], ["doc_id", "score"])

    return docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t")).mapInArrow(tidy(run), "doc_id long, score double")


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    scored = score(docs, train(docs, read_table(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
