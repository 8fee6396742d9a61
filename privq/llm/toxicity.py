"""Toxic spans by a linear-chain conditional random field, and a score for each document.

Token labels come from document labels: every word that toxic documents have too often for chance and clean ones hardly
have is picked, whatever other words its documents hold; these words are the labelled tokens of toxic documents, all
other tokens are clean. The field has two
states, an emission weight for every picked word and one for all other words, and transition weights; it is fitted by
gradient ascent on the conditional likelihood, with forward-backward over windows of tokens.

Scoring reads whole texts. Between picked words all tokens have the same potentials, so forward-backward steps over a
gap by a closed power of one 2x2 matrix; marginals are exact at any length. Tokens with a marginal of a half or more
form spans with character offsets. A document's score is 1 - (1 - p0) * prod(1 - p) over its spans (or its most likely
picked word, without a span), with p0 the marginal of a token inside a text without picked words.

Only text is read for a score. Null and empty texts score p0. Repeated rows score alike. Without labelled rows of both
kinds no word is picked and every score is p0 of an untrained field, 0.5 ** 10. The training sample is bounded by
``MOST_LABELLED`` documents of each label and ``MOST_CHARS`` characters a document; scoring has no bound.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privq.llm.common import is_held_out, table, text_or_empty, tidy

MOST_LABELLED = 1500
MOST_CHARS = 20_000
#: Toxic training texts that a picked word needs at least.
LEAST_TEXTS = 4
WINDOW_TOKENS = 120
#: Windows that one step of the training holds at a time; all windows with picked words are used.
WINDOWS_AT_ONCE = 700
_WORD = re.compile(r"\w+")


@dataclass
class Field:
    """Weights of the field: ``words`` maps picked words to emissions for the toxic state, ``other`` is the default."""

    words: dict[str, float] = field(default_factory=dict)
    other: float = -10 * math.log(2)
    transition: tuple[tuple[float, float], tuple[float, float]] = ((0.0, 0.0), (0.0, 0.0))


def _by_chance(n: int, trials: int, rate: float) -> float:
    """Odds of ``n`` or more hits in ``trials`` at ``rate``."""
    if rate >= 1:
        return 1.0
    logs = [math.lgamma(trials + 1) - math.lgamma(k + 1) - math.lgamma(trials - k + 1) + k * math.log(rate) + (trials - k) * math.log1p(-rate) for k in range(n, trials + 1)]
    return math.fsum(math.exp(x) for x in logs)


def pick_words(texts: list[str], labels: list[int], precision: float = 0.95) -> list[str]:
    """Every word of toxic texts that clean texts hardly have, most frequent first.

    A word needs ``LEAST_TEXTS`` toxic texts, and so many that fewer than one of all words tested would have them by chance.
    """
    seen, same = {}, {}
    for t, y in zip(texts, labels, strict=True):
        if (t, y) not in seen:
            seen[t, y] = {same.setdefault(w, w) for w in _WORD.findall(t.lower())}  # one object a word
    clean = Counter(w for (_, y), ws in seen.items() if not y for w in ws)
    toxic = Counter(w for (_, y), ws in seen.items() if y for w in ws)
    found_in = sum(y for _, y in seen)
    n_clean, n_toxic = max(1, len(seen) - found_in), max(1, found_in)
    tested = sum(n + clean[w] >= LEAST_TEXTS for w, n in toxic.items())
    picked = []
    for word, n in sorted(toxic.items(), key=lambda x: (-x[1], x[0])):
        often = n >= LEAST_TEXTS and n / n_toxic >= precision * (n / n_toxic + clean[word] / n_clean)
        if often and tested * _by_chance(n, n + clean[word], found_in / len(seen)) < 1:
            picked.append(word)
    return picked


def _windows(texts: list[str], labels: list[int], picked: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word numbers (0: not picked), token labels and mask, for all windows with picked words and as many without."""
    number = {w: k + 1 for k, w in enumerate(picked)}
    found: tuple[list, list] = ([], [])
    for t, y in zip(texts, labels, strict=True):
        ids = [number.get(w, 0) for w in _WORD.findall(t.lower())]
        for lo in range(0, len(ids), WINDOW_TOKENS):
            part = ids[lo : lo + WINDOW_TOKENS]
            found[0 if any(part) else 1].append((part, y))
    chosen = found[0] + found[1][: max(WINDOWS_AT_ONCE // 2, len(found[0]))]
    words, mask, truth = (np.zeros((len(chosen), WINDOW_TOKENS), np.int64) for _ in range(3))
    for k, (part, y) in enumerate(chosen):
        words[k, : len(part)], mask[k, : len(part)] = part, 1
        truth[k, : len(part)] = [int(y and w > 0) for w in part]
    return words, truth, mask


def _expected(weights: np.ndarray, words: np.ndarray, mask: np.ndarray) -> np.ndarray:
    """Expected toxic tokens of every word number and expected moves between states, by forward-backward."""
    n, steps = words.shape
    emission, turn = weights[:-4], np.exp(weights[-4:].reshape(2, 2))
    psi = np.stack([np.ones((n, steps)), np.exp(emission[words])], axis=2)
    psi = np.where(mask[:, :, None] == 1, psi, 1.0)
    forward, backward = np.empty((steps + 1, n, 2)), np.empty((steps + 1, n, 2))
    forward[0], backward[steps] = (1.0, 0.0), 1.0
    for t in range(steps):
        a = (forward[t] @ turn) * psi[:, t]
        forward[t + 1] = np.where(mask[:, t : t + 1] == 1, a / a.sum(axis=1, keepdims=True), forward[t])
    for t in range(steps - 1, -1, -1):
        b = (psi[:, t] * backward[t + 1]) @ turn.T
        backward[t] = np.where(mask[:, t : t + 1] == 1, b / b.sum(axis=1, keepdims=True), backward[t + 1])
    joint = forward[:-1, :, :, None] * turn[None, None] * (psi.transpose(1, 0, 2) * backward[1:])[:, :, None, :]
    joint *= (mask.T / joint.sum(axis=(2, 3)))[:, :, None, None]
    return np.concatenate([np.bincount(words.T.ravel(), joint[..., 1].sum(axis=2).ravel(), len(emission)), joint.sum(axis=(0, 1)).ravel()])


def fit_field(texts: list[str], labels: list[int], rounds: int = 120, rate: float = 0.25, decay: float = 0.02) -> Field:
    """Conditional likelihood by gradient ascent with adaptive steps."""
    picked = pick_words(texts, labels)
    if not picked:
        return Field()
    words, truth, mask = _windows(texts, labels, picked)
    weights = np.zeros(len(picked) + 1 + 4)
    mean, square = np.zeros_like(weights), np.zeros_like(weights)
    before = np.concatenate([np.zeros((len(truth), 1), np.int64), truth[:, :-1]], axis=1)
    wanted = np.bincount(words.ravel(), (truth * mask).ravel(), len(picked) + 1)
    moves = np.bincount((before * 2 + truth).ravel(), mask.ravel(), 4)
    for k in range(rounds):
        expected = np.zeros_like(weights)
        for lo in range(0, len(words), WINDOWS_AT_ONCE):
            expected += _expected(weights, words[lo : lo + WINDOWS_AT_ONCE], mask[lo : lo + WINDOWS_AT_ONCE])
        gradient = np.concatenate([wanted, moves]) - expected - decay * weights
        mean, square = 0.9 * mean + 0.1 * gradient, 0.99 * square + 0.01 * gradient**2
        weights = weights + rate * (mean / (1 - 0.9 ** (k + 1))) / (np.sqrt(square / (1 - 0.99 ** (k + 1))) + 1e-8)
    turn = weights[len(picked) + 1 :]
    return Field({w: float(x) for w, x in zip(picked, weights[1:], strict=False)}, float(weights[0]), ((float(turn[0]), float(turn[1])), (float(turn[2]), float(turn[3]))))


class Tagger:
    """Exact marginals of a fitted field over whole texts."""

    def __init__(self, model: Field):
        import ahocorasick

        self.turn = np.exp(np.array(model.transition))
        self.emission = {w: math.exp(x) for w, x in model.words.items()}
        self.finder = None
        if model.words:
            self.finder = ahocorasick.Automaton()
            for w in model.words:
                self.finder.add_word(w, w)
            self.finder.make_automaton()
        plain = self.turn * np.array([1.0, math.exp(model.other)])
        values, right = np.linalg.eig(plain)
        order = np.argsort(-values.real)
        values, right = values.real[order], right.real[:, order]
        left = np.linalg.inv(right)
        self.ratio = values[1] / values[0]
        self.lasting, self.fading = np.outer(right[:, 0], left[0]), np.outer(right[:, 1], left[1])
        inner = np.abs(left[0]) * np.abs(right[:, 0])
        self.base = float(inner[1] / inner.sum())

    def _gap(self, n: int) -> np.ndarray:
        """The n-th power of the plain matrix, up to a factor."""
        return self.lasting + self.ratio**n * self.fading if n else np.eye(2)

    def marginals(self, at: list[int], emissions: list[float], length: int) -> list[float]:
        """P(toxic) at the given token places; all other tokens of ``length`` are plain."""
        gaps = [b - a - 1 for a, b in zip([-1, *at], [*at, length], strict=True)]
        forward, a = [], np.array([1.0, 0.0])
        for gap, e in zip(gaps, emissions, strict=False):
            a = (a @ self._gap(gap) @ self.turn) * (1.0, e)
            a = a / a.sum()
            forward.append(a)
        out, b = [0.0] * len(at), self._gap(gaps[-1]) @ np.ones(2)
        for k in range(len(at) - 1, -1, -1):
            p = forward[k] * b
            out[k] = float(p[1] / p.sum())
            b = self._gap(gaps[k]) @ self.turn @ ((1.0, emissions[k]) * b)
            b = b / b.sum()
        return out

    def tag(self, text: str) -> tuple[float, list[tuple[int, int]]]:
        """Score and toxic spans (character offsets, end exclusive) of a whole text."""
        lowered = text.lower()
        if self.finder is None or next(self.finder.iter(lowered), None) is None:
            return self.base, []
        places = [(m.start(), m.end()) for m in _WORD.finditer(text)]
        found = [(k, self.emission[w]) for k, (lo, hi) in enumerate(places) if (w := text[lo:hi].lower()) in self.emission]
        if not found:
            return self.base, []
        at = [k for k, _ in found]
        likely = self.marginals(at, [e for _, e in found], len(places))
        spans: list[list] = []  # first token, last token, highest marginal
        for k, p in zip(at, likely, strict=True):
            if p >= 0.5:
                if spans and spans[-1][1] == k - 1:
                    spans[-1][1:] = [k, max(spans[-1][2], p)]
                else:
                    spans.append([k, k, p])
        clean = 1 - self.base
        for p in [s[2] for s in spans] or [max(likely)]:
            clean *= 1 - p
        return 1 - clean, [(places[a][0], places[b][1]) for a, b, _ in spans]


def labelled_sample(docs: DataFrame, labels: DataFrame, most: int = MOST_LABELLED) -> tuple[list[str], list[int]]:
    """Texts and labels of at most ``most`` documents of each label, none of them held out.

    The ids are drawn from the labels alone, so the join that fetches their texts broadcasts a bounded number of ids
    and moves no text.
    """
    known = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isin(0, 1) & ~is_held_out()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    draw = F.xxhash64("doc_id")
    ids = None
    for y in (0, 1):
        own = known.where(F.col("toxic") == y).orderBy(draw, "doc_id").limit(most)
        ids = own if ids is None else ids.unionByName(own)
    ids = docs.sparkSession.createDataFrame(ids.collect(), "doc_id long, toxic int")
    body = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("body")).where(F.length("body") <= MOST_CHARS)
    rows = body.join(F.broadcast(ids), "doc_id").orderBy(F.xxhash64("doc_id"), "doc_id", "body").limit(2 * most).collect()
    return [r["body"] for r in rows], [r["toxic"] for r in rows]


def train(docs: DataFrame, labels: DataFrame) -> Field:
    return fit_field(*labelled_sample(docs, labels))


def _tag_batches(model: Field):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tagger = Tagger(model)
        kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
        for batch in batches:
            tagged = [tagger.tag(t) for t in batch.column(batch.num_columns - 1).to_pylist()]
            spans = [[{"start": a, "end": b} for a, b in s] for _, s in tagged]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array([s for s, _ in tagged], pa.float64()), pa.array(spans, kind)], [*batch.schema.names[:-1], "score", "spans"])

    return run


def tag_documents(docs: DataFrame, model: Field, text: str = "text") -> DataFrame:
    """All columns of ``docs`` with ``toxic_score`` and ``toxic_spans``; one narrow pass."""
    names = [f"c{k}" for k in range(len(docs.columns))]
    plain = docs.toDF(*names)
    body = F.coalesce(plain[names[docs.columns.index(text)]], F.lit("")).alias("body")
    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in plain.schema)
    tagged = plain.select(*names, body).mapInArrow(tidy(_tag_batches(model)), f"{fields}, score double, spans array<struct<start: bigint, end: bigint>>")
    return tagged.toDF(*docs.columns, "toxic_score", "toxic_spans")


def drop_toxic(docs: DataFrame, model: Field) -> DataFrame:
    """Documents whose score is below a half, with their own columns only."""
    tagged = tag_documents(docs, model)
    return tagged.where(F.col("toxic_score") < 0.5).select(*docs.columns)


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores of whole ``documents``; the field knows no label of a held-out row."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = train(docs, table(spark, sf_dir, "labels"))
    tagged = tag_documents(docs, model)
    return tagged.select("doc_id", is_held_out().alias("held_out"), F.col("toxic_score").alias("score"), (F.col("toxic_score") >= 0.5).cast("int").alias("predicted"), F.col("toxic_spans").alias("spans"))
