"""Quality by weak labels: overlapping heuristics, accuracies by expectation-maximisation, a hashed linear scorer.

Eight labellers vote good, bad or nothing on each whole text. Only the count of every vote pattern (3^8 at most) leaves
the executors; expectation-maximisation over those counts, which cover all documents, estimates how often each labeller
votes and errs per class. The posterior of a pattern is the soft label with which a hashed linear model is trained on a
bounded sample; the model scores every document from all of its words.

Defined results: a null or wordless text has score 0 and is not kept. A score at the threshold is kept. Repeated
rows are scored each and count in the estimates as often as they occur. An empty table gives an empty result. Extra
columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import hashed_sample, sliced, text_batches

LABELLERS = ("symbols", "pipes", "word_length", "variety", "short_words", "size", "repeated_lines", "sentences")
SLOTS = 1 << 16
#: Training sample of the linear model: rows by hashed id, and the characters of an eligible text.
TRAIN_ROWS, TRAIN_CHARS = 2500, 30_000
#: Score from which a document is kept: low, as a clean text lost costs more than a poor one kept.
KEEP = 0.3
_ODD = re.compile(r"[^\w\s.,;:!?'\"()\-’¿¡]")


def votes(text: str) -> tuple[int, ...]:
    """One vote per labeller: 1 good, -1 bad, 0 none."""
    words = text.split()
    if not words:
        return (-1,) * len(LABELLERS)
    size = np.fromiter(map(len, words), np.int64, len(words))
    n, chars = len(words), int(size.sum())
    odd = len(_ODD.findall(text)) / chars
    pipes = words.count("|") / n
    mean = chars / n
    variety = len(set(words)) / n
    short = int((size <= 3).sum()) / n
    lines = [x for x in text.split("\n") if x.strip()]
    twice = 1 - len(set(lines)) / len(lines)
    ended = sum(x.rstrip()[-1:] in ".!?" for x in lines) / len(lines)
    band = lambda x, good, bad: 1 if good else -1 if bad else 0
    return (
        band(odd, odd < 0.03, odd > 0.1),
        band(pipes, n >= 20 and pipes < 0.01, pipes > 0.1),
        band(mean, 3 <= mean <= 9, mean < 2.5 or mean > 11),
        band(variety, n >= 30 and variety > 0.3, n >= 50 and variety < 0.2),
        band(short, 0.1 <= short <= 0.6, short > 0.8 or n >= 20 and short < 0.03),
        band(n, n >= 40, n < 5),
        band(twice, len(lines) >= 3 and twice < 0.1, twice > 0.3),
        band(ended, ended > 0.7, ended < 0.3),
    )


def estimate(patterns: np.ndarray, counts: np.ndarray, rounds: int = 60) -> tuple[np.ndarray, np.ndarray, float]:
    """Posterior of the good class per pattern, vote tables (labeller, class, vote + 1), prior; labellers start better than chance."""
    m = patterns.shape[1]
    table = np.empty((m, 2, 3))
    for j in range(m):
        seen = [float(counts[patterns[:, j] == v].sum()) + 1 for v in (-1, 0, 1)]
        table[j] = [[seen[0] * 0.7, seen[1], seen[2] * 1.3], [seen[0] * 1.3, seen[1], seen[2] * 0.7]]
    table /= table.sum(axis=2, keepdims=True)
    prior, post = 0.8, None
    for _ in range(rounds):
        log = np.stack([np.log(p) + sum(np.log(table[j, y][patterns[:, j] + 1]) for j in range(m)) for y, p in ((0, prior), (1, 1 - prior))])
        log -= log.max(axis=0)
        like = np.exp(log)
        post = like[0] / like.sum(axis=0)
        prior = float(np.clip((post * counts).sum() / counts.sum(), 0.02, 0.98))
        for y, w in ((0, post * counts), (1, (1 - post) * counts)):
            for j in range(m):
                table[j, y] = [w[patterns[:, j] == v].sum() + 0.5 for v in (-1, 0, 1)]
        table /= table.sum(axis=2, keepdims=True)
    return post, table, prior


class Slots(dict):
    """Word to hashed slot, outer marks as part of its shape; emptied when it holds too many."""

    def __missing__(self, word):
        self[word] = at = _slot(word)
        return at

    def of(self, text: str) -> np.ndarray:
        if len(self) > 300_000:
            self.clear()
        words = text.split()
        at = np.fromiter(map(self.__getitem__, words), np.int64, len(words))
        if len(words) < 2:
            return at
        twice = sum(map(str.__eq__, words, words[1:])) + max(0, len(words) - 4 * len(set(words)))
        return np.concatenate((at, np.full(twice, SLOTS - 1)))  # the last slot: words said again at once, or over four times


def _slot(word: str) -> int:
    if word.isalpha():
        core, marks = word.lower(), ""
    else:
        core = "".join("9" if c.isdigit() else c for c in word.lower() if c.isalnum())
        marks = "".join(c for c in word if not c.isalnum())[:4]
    # Half of the slots hold marks and lengths, which every language shares, half hold words.
    return zlib.crc32(f"{marks}|{min(12, len(core))}".encode("utf-8", "replace")) % (SLOTS // 2) + (SLOTS // 2 - 1) * (not marks and zlib.crc32(core.encode("utf-8", "replace")) % 2)


@dataclass
class Scorer:
    weight: np.ndarray
    bias: float
    posterior: dict[str, float]
    accuracy: list[float]

    def score(self, text: str, cache: Slots) -> float:
        at = cache.of(text)
        if not at.size:
            return 0.0
        return float(1 / (1 + np.exp(-np.clip(self.weight[at].sum() / at.size * 8 + self.bias, -30, 30))))


def fit(texts: list[str], soft: np.ndarray, rounds: int = 300) -> tuple[np.ndarray, float]:
    """Weights of the hashed linear model for soft labels; each text's slots count by their share."""
    cache = Slots()
    each = [cache.of(t) for t in texts]
    at = np.concatenate(each)
    share = np.repeat([8 / max(1, len(e)) for e in each], [len(e) for e in each])
    row = np.repeat(np.arange(len(each)), [len(e) for e in each])
    key, where = np.unique(row * SLOTS + at, return_inverse=True)
    x, row, at = np.bincount(where, weights=share), key // SLOTS, key % SLOTS
    w, b, grad2, rate = np.zeros(SLOTS), 0.0, np.full(SLOTS, 1e-6), 0.3
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(np.bincount(row, weights=x * w[at], minlength=len(each)) + b, -30, 30)))
        d = (p - soft) / len(each)
        g = np.bincount(at, weights=x * d[row], minlength=SLOTS) + 1e-5 * w
        grad2 += g * g
        w -= rate * g / np.sqrt(grad2)
        b -= 2 * float(d.sum())
    return w, b


def _vote_rows(batches):
    for batch in sliced(batches):
        texts = batch.column("text").to_pylist()
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(["".join("-0+"[v + 1] for v in votes(t or "")) for t in texts], pa.string())], names=["doc_id", "votes"])


def train(docs: DataFrame) -> Scorer | None:
    """Estimates over the votes on all documents; linear model from a bounded sample of them."""
    text_batches(docs.sparkSession)
    rows = docs.select("doc_id", "text")
    found = rows.mapInArrow(_vote_rows, "doc_id long, votes string").groupBy("votes").agg(F.count("*").alias("n")).collect()  # 3^8 rows at most
    if not found:
        return None
    patterns = np.array([["-0+".index(c) - 1 for c in r["votes"]] for r in found])
    post, table, _ = estimate(patterns, np.array([float(r["n"]) for r in found]))
    posterior = {r["votes"]: float(p) for r, p in zip(found, post)}
    texts = [r["text"] for r in hashed_sample(rows, TRAIN_ROWS, "doc_id", "text", salt=2).filter(F.length("text").between(1, TRAIN_CHARS)).collect()]
    texts = sorted(t for t in texts if t.split())
    if not texts:
        return None
    soft = np.array([posterior["".join("-0+"[v + 1] for v in votes(t))] for t in texts])
    w, b = fit(texts, soft)
    return Scorer(w, b, posterior, [float(table[j, 0, 2] / max(1e-9, table[j, 0, 0] + table[j, 0, 2])) for j in range(len(LABELLERS))])


def scorer(shared):
    def run(batches):
        model: Scorer = shared.value
        cache = Slots()
        for batch in sliced(batches):
            texts = [t or "" for t in batch.column("text").to_pylist()]
            seen = ["".join("-0+"[v + 1] for v in votes(t)) for t in texts]
            score = [model.score(t, cache) if model else 0.0 for t in texts]
            post = [model.posterior.get(v) if model else None for v in seen]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(seen, pa.string()), pa.array(post, pa.float64()), pa.array(score, pa.float64()), pa.array([s >= KEEP for s in score], pa.bool_())], names=["doc_id", "votes", "posterior", "score", "kept"])

    return run


def classify(docs: DataFrame) -> DataFrame:
    """doc_id, votes, posterior of the votes, score of the linear model, kept, for every document."""
    shared = docs.sparkSession.sparkContext.broadcast(train(docs))  # fixed tables
    return docs.select("doc_id", "text").mapInArrow(scorer(shared), "doc_id long, votes string, posterior double, score double, kept boolean")
