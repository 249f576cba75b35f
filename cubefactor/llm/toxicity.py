"""Toxicity: a subsequence string-kernel support vector machine with Nystroem landmarks.

The kernel compares two words by the letter triples that both contain in order, with or without gaps;
each triple weighs `decay` to the power of the span it covers, so inserted characters ("id-i.ot") cost a
little and never hide a match. The machine is linear in the kernel values of its landmarks, so all of
them fold into one weight per triple: scoring a word sums the weights of its triples, whatever the number
of landmarks. A sentence scores as its strongest word, a document as its strongest sentence, so as its
strongest word: where sentences end changes no score.

It learns from labelled documents (`max_train_rows` of them), read sentence by sentence. Labels are given for
documents, not for sentences or words, so the machine's instances are words: those of clean documents are
clean; which words of toxic documents are insults is guessed from how much more often toxic documents hold
them, then found in turns with the machine (multiple-instance learning).

Defined cases: repeated rows are scored alike and learned from once for each row; ties in frequency go by the
word itself; null and empty texts get the score of a text without words; words longer than `WINDOW`
characters are read in overlapping windows, so no text is cut; an empty table gives no rows; labels of one
class give that class's smoothed share to all; a null doc_id is kept and not held out; extra columns are
ignored.
"""

from __future__ import annotations

import pickle
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, crc_fold, ship_package, text_or_empty
from .quality import labelled_sample

#: Characters of a word that one window holds, and the step between windows of longer words.
WINDOW, STEP = 18, 9
#: Mark at both ends of a word; no word holds it, as it separates words.
EDGE = "\x20"
#: Longest span of a matched triple.
SPAN = 7
#: Margin from which a word counts as an insult.
HIT = 0.3
#: Slots of the folded weight table.
SLOTS = 1 << 20
#: Splits into words; ends of sentences. Fixed patterns.
MARKS, WORD_BREAK, SENTENCE_BREAK = r"[^\p{L}\p{N}]+", r"[\x20\x09-\x0D]+", r"[.!?\n]+[\x20\x09-\x0D]*"
_TRIPLES = np.array([t for t in combinations(range(WINDOW), 3) if t[2] - t[0] < SPAN], np.int64)


def windows(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Zero-padded code points of the windows of each word, and the number of the word each is from.

    Words carry marks at both ends, so that a stem at the front differs from the same letters inside.
    """
    owner, parts = [], []
    for number, word in enumerate(words):
        word = f"{EDGE}{word}{EDGE}"
        if len(word) <= WINDOW:
            owner.append(number)
            parts.append(word)
        else:
            for at in range(0, len(word) - STEP, STEP):
                owner.append(number)
                parts.append(word[at : at + WINDOW])
    if not parts:
        return np.zeros((0, WINDOW), np.uint32), np.zeros(0, np.int64)
    table = np.array(parts, f"U{WINDOW}").view(np.uint32).reshape(len(parts), WINDOW)
    return table, np.array(owner, np.int64)


def _slots(table: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Slot of every triple of every window, and whether it lies within the word."""
    a, b, c = (table[:, _TRIPLES[:, k]].astype(np.uint64) for k in range(3))
    code = (a * np.uint64(0x9E3779B97F4A7C15)) ^ (b * np.uint64(0xC2B2AE3D27D4EB4F)) ^ (c * np.uint64(0x165667B19E3779F9))
    code ^= code >> np.uint64(29)
    code *= np.uint64(0xBF58476D1CE4E5B9)
    return (code >> np.uint64(44)).astype(np.int64), c != 0


def _decays(decay: float) -> np.ndarray:
    return decay ** (_TRIPLES[:, 2] - _TRIPLES[:, 0] + 1.0)


def features(table: np.ndarray, decay: float) -> tuple[np.ndarray, np.ndarray]:
    """Slots and weights of the unit-length kernel vector of each window; a repeated triple adds up."""
    slots, inside = _slots(table)
    weights = np.where(inside, _decays(decay), 0.0)
    order = np.argsort(slots, 1)
    ranked, heavy = np.take_along_axis(slots, order, 1), np.take_along_axis(weights, order, 1)
    fresh = np.ones_like(ranked, bool)
    fresh[:, 1:] = ranked[:, 1:] != ranked[:, :-1]
    run = np.cumsum(fresh.ravel()) - 1
    sums = np.bincount(run, heavy.ravel())
    norm = np.sqrt(np.add.reduceat(sums**2, run.reshape(ranked.shape)[:, 0])) if len(table) else np.zeros(0)
    return slots, weights / np.maximum(norm, 1e-9)[:, None]


def kernel(left: list[str], right: list[str], decay: float = 0.7) -> np.ndarray:
    """Normalised kernel values between the first windows of words; used for landmarks and in tests."""
    def rows(words):
        table, owner = windows(words)
        first = np.unique(owner, return_index=True)[1]
        return features(table[first], decay)

    (ls, lw), (rs, rw) = rows(left), rows(right)
    out = np.zeros((len(left), len(right)))
    dense = np.zeros(SLOTS)
    for j in range(len(right)):
        np.add.at(dense, rs[j], rw[j])
        out[:, j] = (dense[ls] * lw).sum(1)
        dense[rs[j]] = 0
    return out


@dataclass
class KernelMachine:
    """Landmark coefficients folded into one weight per triple slot; slope and offset turn margins into scores."""

    weights: np.ndarray
    bias: float
    calibration: np.ndarray
    decay: float
    landmarks: list[str]

    def margins(self, words: list[str], step: int = 20_000) -> np.ndarray:
        out = np.full(len(words), -1e9)
        for at in range(0, len(words), step):
            table, owner = windows(words[at : at + step])
            if len(table):
                slots, weights = features(table, self.decay)
                np.maximum.at(out, owner + at, (self.weights[slots] * weights).sum(1) + self.bias)
        return out

    def score(self, evidence: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(evidence @ self.calibration, -40, 40)))


def evidence_of(strongest: np.ndarray, hits: np.ndarray, words: np.ndarray) -> np.ndarray:
    """What calibration weighs: the strongest word, how many words count as insults, the length, and one."""
    return np.column_stack([np.clip(strongest, -2, 2), np.log1p(hits), np.log1p(words), np.ones(len(hits))])


def _plain(words: pa.Array) -> pa.Array:
    """Lower-case letters and digits of each word; signs put between letters fall away."""
    return pc.replace_substring_regex(pc.utf8_lower(words), MARKS, "")


def _sentence(text: str, known: dict[str, str]) -> list[str]:
    """Words of a sentence; equal words are one object."""
    words = ("".join(c for c in w if c.isalnum()) for w in text.lower().split())
    return [known.setdefault(w, w) for w in words if w]


def text_evidence(texts: pa.Array, machine: KernelMachine, seen: dict[str, float]) -> np.ndarray:
    """Evidence from every word of each whole text; a text without words counts as one empty word."""
    split = pc.split_pattern_regex(texts.fill_null(""), WORD_BREAK)
    words = split.flatten().dictionary_encode()
    names = _plain(words.dictionary).to_pylist()
    fresh = list(dict.fromkeys(w for w in names if w not in seen))
    known = dict(zip(fresh, machine.margins(fresh).tolist(), strict=True))
    for w in fresh[: max(0, 150_000 - len(seen))]:  # the most common words come early; the bound keeps workers small
        seen[w] = known[w]
    table = np.fromiter((known[w] if w in known else seen[w] for w in names), float, len(names))
    bounds = np.asarray(split.offsets).astype(np.int64)
    if not len(texts):
        return np.zeros((0, 4))
    margin, first = table[np.asarray(words.indices)], bounds[:-1] - bounds[0]
    hits = np.add.reduceat((margin > HIT).astype(np.int64), first)
    return evidence_of(np.maximum.reduceat(margin, first), hits, np.diff(bounds))


def _train_machine(x: np.ndarray, y: np.ndarray, *, cost: float, rounds: int = 30) -> tuple[np.ndarray, float]:
    """Dual coordinate descent for the squared-hinge linear SVM; classes weigh the same in total."""
    n = len(y)
    data = np.hstack([x, np.ones((n, 1))])
    weight = np.where(y > 0, n / (2 * max((y > 0).sum(), 1)), n / (2 * max((y < 0).sum(), 1)))
    soft = 1 / (2 * cost * weight)
    diagonal = (data**2).sum(1) + soft
    alpha, w = np.zeros(n), np.zeros(data.shape[1])
    rng = np.random.default_rng(7)
    for _ in range(rounds):
        moved = 0.0
        for i in rng.permutation(n):
            gradient = y[i] * (data[i] @ w) - 1 + soft[i] * alpha[i]
            step = max(alpha[i] - gradient / diagonal[i], 0.0) - alpha[i]
            if step:
                alpha[i] += step
                w += step * y[i] * data[i]
                moved = max(moved, abs(step))
        if moved < 1e-3:
            break
    return w[:-1], float(w[-1])


def fit_machine(texts: list[str], labels: list[int], *, landmarks: int = 384, decay: float = 0.7, cost: float = 10.0, turns: int = 3, max_words: int = 2500) -> KernelMachine:
    """Learn from labelled documents, sentence by sentence. Deterministic for a set of rows, whatever their order."""
    order = sorted(range(len(texts)), key=lambda i: (labels[i], texts[i]))
    texts = [texts[i] for i in order]
    labels = [labels[i] for i in order]
    known: dict[str, str] = {}
    sentences = [[_sentence(part, known) for part in re.split(SENTENCE_BREAK, text)] for text in texts]
    toxic = [d for d, label in zip(sentences, labels, strict=True) if label == 1]
    clean = [d for d, label in zip(sentences, labels, strict=True) if label == 0]
    share = (len(toxic) + 1) / (len(texts) + 2) if texts else 0.5
    if not toxic or not clean:
        return KernelMachine(np.zeros(SLOTS), 0.0, np.array([0, 0, 0, np.log(share / (1 - share))]), decay, [])
    in_clean = Counter(w for d in clean for w in {w for s in d for w in s})
    documents = [{w for s in d for w in s} for d in toxic]
    in_toxic = Counter(w for d in documents for w in d)
    # The first guess: words that explain most toxic documents not explained yet and are rare in clean ones.
    telling = [w for w, n in in_toxic.items() if n >= max(4, len(toxic) // 50) and n * len(clean) > 20 * (in_clean[w] + 1) * len(toxic)]
    left, witnesses = set(range(len(documents))), []
    where: dict[str, list[int]] = {}
    for number, d in enumerate(documents):
        for w in d:
            if in_toxic[w] >= 2 and in_toxic[w] * len(clean) > 8 * in_clean[w] * len(toxic):
                where.setdefault(w, []).append(number)
    while left and len(witnesses) < landmarks * 2 // 3:
        best = max(where, key=lambda w: (sum(i in left for i in where[w]), w), default=None)
        if best is None or not (found := [i for i in where[best] if i in left]):
            break
        witnesses.append(best)
        left.difference_update(found)
    rng = np.random.default_rng(11)
    common = sorted(in_clean, key=lambda w: (-in_clean[w], w))
    plain = [w for w in common if len(w) > 3][: 8 * landmarks]
    plain = [plain[i] for i in rng.permutation(len(plain))]
    names = sorted(set(in_clean) | set(in_toxic))
    witnesses = list(dict.fromkeys([*witnesses, *sorted(telling, key=lambda w: (-in_toxic[w], w))]))[:max_words]
    positive, hard, machine, margin = witnesses or sorted(in_toxic, key=lambda w: (-in_toxic[w], w))[:8], [], None, {}
    for _ in range(turns):
        marks = list(dict.fromkeys([*positive[: landmarks // 2], *hard[: landmarks // 4], *plain]))[:landmarks]
        values, vectors = np.linalg.eigh(kernel(marks, marks, decay))
        keep = values > 1e-4
        whiten = vectors[:, keep] / np.sqrt(values[keep])
        negative = [w for w in dict.fromkeys([*hard, *common[:max_words]]) if w not in set(positive)]
        words = [*positive, *negative]
        y = np.array([1.0] * len(positive) + [-1.0] * len(negative))
        w, bias = _train_machine(kernel(words, marks, decay) @ whiten, y, cost=cost)
        table, owner = windows(marks)
        mark_slots, mark_weights = features(table[np.unique(owner, return_index=True)[1]], decay)
        folded = np.zeros(SLOTS)
        for coefficient, slots, weights in zip(whiten @ w, mark_slots, mark_weights, strict=True):
            np.add.at(folded, slots, coefficient * weights)
        machine = KernelMachine(folded, bias, np.zeros(4), decay, marks)
        margin = dict(zip(names, machine.margins(names).tolist(), strict=True))
        # Every sentence of a toxic document that looks as bad as its worst one tells more insults.
        worst = Counter(w for d in documents for w in d if margin[w] > -0.5 and in_toxic[w] * len(clean) > 6 * in_clean[w] * len(toxic) and in_toxic[w] > 1)
        found = Counter(max((w for w in d), key=lambda w: (margin[w], w)) for d in documents if d)
        worst.update({w: n for w, n in found.items() if in_toxic[w] * len(clean) > 6 * in_clean[w] * len(toxic)})
        worst.update({w: in_toxic[w] for w in telling})
        positive = [w for w, _ in sorted(worst.items(), key=lambda x: (-x[1], x[0]))][:max_words] or positive
        hard = sorted(in_clean, key=lambda w: (-margin[w], w))[:max_words]
    def evidence(group: list[list[list[str]]]) -> np.ndarray:
        margins = [np.array([margin[w] for s in d for w in s] or [-2.0]) for d in group]
        return evidence_of(np.array([m.max() for m in margins]), np.array([(m > HIT).sum() for m in margins]), np.array([len(m) for m in margins]))

    x = np.vstack([evidence(toxic), evidence(clean)])
    target = np.array([1.0 - 1 / (len(toxic) + 2)] * len(toxic) + [1 / (len(clean) + 2)] * len(clean))
    ridge = np.diag([1e-2, 1e-2, 1e-2, 1e-6])
    for _ in range(50):  # logistic calibration by Newton steps
        chance = machine.score(x)
        curve = chance * (1 - chance) + 1e-9
        move = np.linalg.solve((x * curve[:, None]).T @ x + ridge, x.T @ (target - chance) - ridge @ machine.calibration)
        machine.calibration = machine.calibration + np.clip(move, -3, 3)
        if abs(move).max() < 1e-8:
            break
    return machine


def fit_toxicity(docs: DataFrame, labels: DataFrame, *, target: str = "toxic", fold: int = 3, held: int = 1, max_train_rows: int = 4000, **options) -> KernelMachine:
    """Fit in one executor task on at most `max_train_rows` labelled documents outside the held-out fold."""
    ship_package(docs.sparkSession)
    sample = labelled_sample(docs, labels, target, crc_fold(F.col("doc_id"), fold) != held, max_train_rows).select("text", "label")

    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        texts, marks = [], []
        for batch in batches:
            texts += batch.column(0).to_pylist()
            marks += batch.column(1).to_pylist()
        if texts:
            yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(fit_machine(texts, marks, **options))], pa.binary())], ["machine"])

    found = sample.repartition(1).mapInArrow(learn, "machine binary").collect()
    return pickle.loads(found[0]["machine"]) if found else fit_machine([], [], **options)


def score_toxicity(docs: DataFrame, machine: KernelMachine) -> DataFrame:
    """doc_id and score for every row of `docs`."""
    ship_package(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(machine)  # of fixed size: SLOTS weights

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[str, float] = {}
        for part in chunks(batches, limit=2 << 20):
            evidence = text_evidence(part.column(1), shared.value, seen)
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(shared.value.score(evidence))], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long"), text_or_empty().alias("text")).mapInArrow(score, "doc_id long, score double")


def classify_toxicity(docs: DataFrame, labels: DataFrame, *, threshold: float = 0.7, fold: int = 3, held: int = 1, **options) -> DataFrame:
    """doc_id, held_out, score and predicted for every document."""
    scored = score_toxicity(docs, fit_toxicity(docs, labels, fold=fold, held=held, **options))
    return scored.select(
        "doc_id",
        F.coalesce(crc_fold(F.col("doc_id"), fold) == held, F.lit(False)).alias("held_out"),
        "score",
        (F.col("score") >= threshold).cast("int").alias("predicted"),
    )
