"""Toxicity: a lexicon trie met by Levenshtein automata, and windows of context.

The lexicon holds words and stems (a stem matches any word that begins with
it). It starts from a short fixed list and grows by words and stems that mark
toxic documents in a bounded sample of labelled rows. All words within one
edit, at any letter, of a lexicon word of ``EDIT_LENGTH`` letters or more are
accepted by the product of the trie and the Levenshtein automaton, which is
made deterministic state by state as texts ask for it; most words leave it
within a few letters. Shorter words and stems match as they are; the words
behind a learned stem are in the lexicon themselves, so they take edits too.

Each hit is weighed by its window: quotation marks around it or reporting
words near it speak for quotation, words of address for abuse. A logistic
model over the sums of these weights, fitted on the same sample, gives the
score. Scores depend on the text alone.

Null and empty texts have no hit and get the model's lowest score. With no
labelled rows a fixed model is used. Repeated rows are scored each for
itself; an empty table gives an empty result.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from warpspan.llm.common import cut, values

# Words of abuse to start from, and words that mark context.
SEED_WORDS = ("trash", "pathetic", "idiot", "worthless", "disgusting", "stupid", "clown", "loser", "scum", "moron")
REPORTING = frozenset("said says quote quoted quoting word words term called wrote phrase meaning definition zitat cita citation".split())
ADDRESS = frozenset("you your youre u du dich dein ihr tu te toi vous ton tú usted eres are".split())
MARKS = "\"'“”„«»‘’"

#: Labelled rows that the lexicon and the model are fitted on, at most.
SAMPLE_ROWS = 20_000
#: Learned entries of the lexicon, at most; the words behind its stems come on top.
ENTRIES = 200
#: Share of the toxic documents that a learned entry must occur in.
LEAST_SHARE = 0.01
#: Lexicon words at least this long may be one edit away.
EDIT_LENGTH = 4
REACH = 4

_WORD = re.compile(r"\w+")


class Entry(NamedTuple):
    text: str
    stem: bool
    weight: float


class LexiconAutomaton:
    """Accepts words within one edit of a lexicon word, or that begin with a stem."""

    def __init__(self, entries: list[Entry]):
        self.entries = entries
        self.children: list[dict[str, int]] = [{}]
        self.ends: list[list[int]] = [[]]
        self.editable: list[bool] = [False]
        for number, entry in enumerate(entries):
            self._insert(number, entry)
        # A deterministic state is the set of (node, edits) it stands for.
        self.moves: dict[frozenset, dict[str, frozenset]] = {}
        self.start = self._close({(0, 0)})

    def _insert(self, number: int, entry: Entry) -> None:
        node = 0
        may_edit = not entry.stem and len(entry.text) >= EDIT_LENGTH
        self.editable[0] |= may_edit
        for letter in entry.text:
            if letter not in self.children[node]:
                self.children[node][letter] = len(self.children)
                self.children.append({})
                self.ends.append([])
                self.editable.append(False)
            node = self.children[node][letter]
            self.editable[node] |= may_edit
        self.ends[node].append(number)

    def _close(self, states: set[tuple[int, int]]) -> frozenset:
        """Adds what is reached by leaving out one lexicon letter."""
        more = {
            (child, 1)
            for node, edits in states
            if edits == 0
            for child in self.children[node].values()
            if self.editable[child]
        }
        return frozenset(states | more)

    def _step(self, state: frozenset, letter: str) -> frozenset:
        out: set[tuple[int, int]] = set()
        for node, edits in state:
            child = self.children[node].get(letter)
            if child is not None and (edits == 0 or self.editable[child]):
                out.add((child, edits))
            if edits == 0:
                out.update((c, 1) for c in self.children[node].values() if self.editable[c])
                if self.editable[node]:
                    out.add((node, 1))
        return self._close(out)

    def match(self, word: str) -> tuple[int, int] | None:
        """The entry with the fewest edits, then the largest weight, and its edits."""
        state, best = self.start, None

        def better(number: int, edits: int):
            key = (edits, -self.entries[number].weight, number)
            return key if best is None or key < best else best

        for letter in word:
            known = self.moves.setdefault(state, {})
            state = known.get(letter) if letter in known else known.setdefault(letter, self._step(state, letter))
            if not state:
                break
            for node, edits in state:
                if edits == 0:
                    for number in self.ends[node]:
                        if self.entries[number].stem:
                            best = better(number, 0)
        else:
            for node, edits in state:
                for number in self.ends[node]:
                    entry = self.entries[number]
                    if edits == 0 or not entry.stem and len(entry.text) >= EDIT_LENGTH:
                        best = better(number, edits)
        return None if best is None else (best[2], best[0])


class _Memo(dict):
    """Matches by word, computed once each; emptied when it gets large."""

    def __init__(self, automaton: LexiconAutomaton, most: int = 1_000_000):
        super().__init__()
        self.automaton, self.most = automaton, most

    def __missing__(self, word: str):
        if len(self) >= self.most:
            self.clear()
        self[word] = found = self.automaton.match(word)
        return found


FEATURES = ("abuse", "abuse_log", "kinds", "misspelled", "quoted", "rate")


def features(text: str | None, memo: _Memo) -> list[float]:
    """Sums over the hits of a text, each weighed by its context."""
    lowered = (text or "").lower()
    words = _WORD.findall(lowered)
    at = [k for k, w in enumerate(words) if memo[w] is not None]
    if not at:
        return [0.0] * len(FEATURES)
    places = [m.span() for m in _WORD.finditer(lowered)]
    abuse = misspelled = quoted = 0.0
    kinds = set()
    for k in at:
        number, edits = memo[words[k]]
        entry = memo.automaton.entries[number]
        near = set(words[max(0, k - REACH) : k] + words[k + 1 : k + 1 + REACH])
        start, end = places[k]
        marked = start > 0 and lowered[start - 1] in MARKS and end < len(lowered) and lowered[end] in MARKS
        weight = entry.weight * (0.5 if edits else 1.0)
        if marked or near & REPORTING:
            quoted += weight
            weight *= 0.3
        elif near & ADDRESS:
            weight *= 1.2
        misspelled += edits
        abuse += weight
        kinds.add(number)
    return [min(abuse, 60.0) / 10, math.log1p(abuse), math.log1p(len(kinds)), math.log1p(misspelled), math.log1p(quoted), 10 * abuse / (len(words) + 20)]


class Model(NamedTuple):
    entries: list[Entry]
    bias: float
    slopes: tuple[float, ...]


#: What is used where there is nothing to learn from.
FIXED = Model([Entry(w, False, 3.0) for w in SEED_WORDS], -4.0, (1.0, 1.5, 1.0, 0.0, -0.5, 0.0))


def train_rows(documents: DataFrame, labels: DataFrame, may_learn: Column, most: int = SAMPLE_ROWS) -> DataFrame:
    """``text, toxic`` of at most ``most`` labelled documents, the first by a hash of the id; of equal texts one."""
    known = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & may_learn)
    chosen = known.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    rows = documents.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")
    alike = rows.groupBy(F.xxhash64("text"), F.crc32(F.col("text").cast("binary")))
    return alike.agg(F.max_by("text", "doc_id").alias("text"), F.max("toxic").alias("toxic")).select("text", "toxic")


def _marks(text: str) -> set[str]:
    """What a document shows: its words, and their stems with a star."""
    words = set(_WORD.findall(text.lower()))
    stems = {f"{w[:n]}*" for w in words for n in range(3, min(9, len(w)))}
    return words | stems


def learn_entries(rows: DataFrame, most: int = ENTRIES) -> list[Entry]:
    """Words and stems that mark toxic documents, strongest first; at most ``most`` rows come to the driver."""

    def count(source):
        for batch in source:
            toxic: Counter = Counter()
            clean: Counter = Counter()
            for text, label in zip(values(batch.column(0)), values(batch.column(1)), strict=True):
                (toxic if label else clean).update(_marks(text or ""))
            names = list(toxic.keys() | clean.keys())
            yield pa.record_batch(
                [pa.array(names, pa.string()), pa.array([toxic[x] for x in names], pa.int64()), pa.array([clean[x] for x in names], pa.int64())],
                names=["mark", "toxic", "clean"],
            )

    size = rows.agg(F.sum("toxic").alias("toxic"), F.count("*").alias("n")).first()
    n_toxic, n_clean = size.toxic or 0, (size.n or 0) - (size.toxic or 0)
    if not n_toxic or not n_clean:
        return []
    counts = rows.select("text", "toxic").mapInArrow(count, "mark string, toxic bigint, clean bigint")
    total = counts.groupBy("mark").agg(F.sum("toxic").alias("t"), F.sum("clean").alias("c"))
    odds = F.log((F.col("t") + 0.5) / (n_toxic + 1)) - F.log((F.col("c") + 0.5) / (n_clean + 1))
    # Support in toxic documents beyond chance, and far more often there than elsewhere.
    marked = cut(
        total.where((F.col("t") >= max(5, math.ceil(LEAST_SHARE * n_toxic))) & (F.col("t") * n_clean >= 12 * (F.col("c") + 0.5) * n_toxic))
        .withColumn("odds", odds)
        .withColumn("gain", F.col("t") * odds)
    )
    order = (F.desc("gain"), F.length("mark").desc(), "mark")
    found = marked.orderBy(*order).limit(most * 4).collect()
    whole = marked.where(~F.col("mark").endswith("*")).orderBy(*order).limit(most * 4).collect()
    # Of marks that say the same the longest stays: a stem is left out if a
    # longer entry has nearly all its documents, a word if its stem is there.
    chosen: list[tuple[Entry, int]] = []
    for row in found:
        text, stem = (row.mark[:-1], True) if row.mark.endswith("*") else (row.mark, False)
        known = any(e.stem and text.startswith(e.text) or e.text.startswith(text) and row.t <= 1.05 * t for e, t in chosen)
        if not known and len(chosen) < most:
            chosen.append((Entry(text, stem, row.odds), row.t))
    entries = [entry for entry, _ in chosen]
    # Stems take no edits, so the words behind them stay as well.
    stems = tuple(e.text for e in entries if e.stem)
    return entries + [Entry(row.mark, False, row.odds) for row in whole if row.mark.startswith(stems)]


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, rounds: int = 40) -> tuple[float, tuple[float, ...]]:
    """Bias and slopes by Newton's method with a small ridge."""
    full = np.hstack([np.ones((len(x), 1)), x])
    beta = np.zeros(full.shape[1])
    keep = np.diag([1e-6] + [ridge * len(x) / 100] * x.shape[1]) + 1e-9 * np.eye(full.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(full @ beta, -30, 30)))
        slope = full.T @ (p - y) + keep @ beta
        curve = (full * (p * (1 - p) + 1e-9)[:, None]).T @ full + keep
        step = np.linalg.solve(curve, slope)
        size = np.abs(step).max()
        beta -= step * min(1.0, 4.0 / max(size, 1e-12))
        if size < 1e-8:
            break
    return float(beta[0]), tuple(map(float, beta[1:]))


def fit(documents: DataFrame, labels: DataFrame, may_learn: Column | None = None, most: int = SAMPLE_ROWS) -> Model:
    """Lexicon and model from labelled rows where ``may_learn`` (a column of labels) holds."""
    rows = train_rows(documents, labels, F.lit(True) if may_learn is None else may_learn, most)
    learned = learn_entries(rows)
    if not learned:
        return FIXED
    have = {e.text for e in learned if not e.stem}
    entries = learned + [Entry(w, False, 3.0) for w in SEED_WORDS if w not in have]

    def measured(source):
        memo = _Memo(LexiconAutomaton(entries))
        for batch in source:
            x = [features(t, memo) for t in values(batch.column(0))]
            yield pa.record_batch([pa.array(x, pa.list_(pa.float64())), batch.column(1).cast(pa.int32())], names=["x", "toxic"])

    table = rows.select("text", F.col("toxic").cast("int")).mapInArrow(measured, "x array<double>, toxic int").toArrow()
    x, y = np.array(table.column("x").to_pylist()), table.column("toxic").to_numpy().astype(float)
    return Model(entries, *fit_logistic(x, y))


def score(text: str | Column, model: Model) -> Column:
    """The model's probability that a text is toxic, from 0 to 1."""
    ready: list[_Memo] = []

    @F.arrow_udf("double")
    def scored(texts: pa.Array) -> pa.Array:
        if not ready:
            ready.append(_Memo(LexiconAutomaton(model.entries)))
        x = np.array([features(t, ready[0]) for t in values(texts)]).reshape(-1, len(FEATURES))
        return pa.array(1 / (1 + np.exp(-np.clip(model.bias + x @ np.array(model.slopes), -30, 30))))

    return scored(F.col(text) if isinstance(text, str) else text)


def held_out(doc_id: Column) -> Column:
    """Whether an id belongs to the fold that nothing is learned from."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def score_documents(documents: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """``doc_id, held_out, score, predicted`` of every document, learned outside the held-out fold."""
    model = fit(documents, labels, ~held_out(F.col("doc_id")))
    scored = documents.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), score("text", model).alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))
