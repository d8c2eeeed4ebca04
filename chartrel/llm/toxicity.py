"""Toxicity by a bidirectional gated recurrent network with attention pooling, written and trained in numpy.

Inputs of a word are a learned vector of its own, the mean of learned vectors of its character 3- to 5-grams (one hashed table,
trained with the network), its log odds, and the strongest and the mean log odds of its n-grams. Odds that the network
learns from are counted without the text's own part of the sample, so no input holds its own label, and a part of the sample
that neither counts nor trains calibrates the score. Windows of 32 words start every 20 words, so all overlap; each is scored, and the strongest
window, calibrated, is the score of the whole text. Labels are learned from a bounded sample of the
training rows, and the intercept is moved from the sample's share of toxic rows to that of all training labels; every
word of every document is scored. A word of more than ``LONGEST`` letters and digits is read as overlapping pieces, each
a step of the network, so a text without blanks is scored to its end.

Defined results: a null or wordless text has score 0 and is not toxic. Labels that are null, neither 0 nor 1, or of
unknown documents are ignored; of several labels of one id the highest counts. Without both classes to learn from every
score is 0. Repeated rows are scored each. Extra columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fold, mix, sliced, slices, text_batches, trim

WINDOW, STRIDE, HIDDEN, VECTOR = 32, 20, 8, 8
GRAMS = (3, 4, 5)
TABLE = 1 << 20
#: Bounds of the training sample: toxic rows, other rows, and the characters up to which a text is eligible for it.
POSITIVES, NEGATIVES, TRAIN_CHARS = 1000, 2000, 20_000
THRESHOLD = 0.3
#: Words of a worker's table, words brought to it at once, windows scored at once.
VOCABULARY, TOKENS, AT_ONCE = 60_000, 50_000, 1024
INPUTS = 4 + 2 * VECTOR
#: Slots of the learned table; parts of the sample whose odds are counted without them; one text of so many calibrates.
SLOTS, PARTS, HELD = 1 << 14, 4, 5
#: Letters and digits of one step at most, those that neighbouring pieces of a longer word share, characters whose inputs are made at once.
LONGEST, SHARED, CHARS = 200, 8, 1 << 19


def _hashed(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of the words, of all their n-grams (a mark at both ends), and where each word's n-grams begin."""
    text = "".join(f"\x02{w}\x03" for w in words)
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    size = np.array([len(w) + 2 for w in words])
    start = np.cumsum(size) - size
    with np.errstate(over="ignore"):
        x = mix(codes)
        place = np.arange(len(codes)) - np.repeat(start, size)
        whole = mix(np.add.reduceat(x * (mix(place) | np.uint64(1)), start)) if len(words) else np.zeros(0, np.uint64)
        room = np.repeat(size, size) - place
        found, owner = [], []
        own = np.repeat(np.arange(len(words)), size)
        for n in GRAMS:
            h = np.full(max(0, len(x) - n + 1), n, np.uint64)
            for j in range(n):
                h = h * np.uint64(0x9DDFEA08EB382D69) + x[j : j + len(h)]
            ok = room[: len(h)] >= n
            found.append(mix(h[ok]))
            owner.append(own[: len(h)][ok])
    h, o = np.concatenate(found), np.concatenate(owner)
    at = np.argsort(o, kind="stable")
    return whole, h[at], np.searchsorted(o[at], np.arange(len(words)))


def _plain(word: str) -> str:
    return "".join(c for c in word.lower() if c.isalnum()) if not word.isalpha() else word.lower()


def words_of(text: str | None) -> list[str]:
    """Words between blanks; the letters and digits of one longer than LONGEST in pieces that share SHARED of them."""
    words = (text or "").split()
    if max(map(len, words), default=0) <= LONGEST:
        return words
    out = []
    for w in words:
        p = _plain(w) if len(w) > LONGEST else ""
        out += [p[i : i + LONGEST] for i in range(0, len(p) - SHARED, LONGEST - SHARED)] if len(p) > LONGEST else [w]
    return out


def _marks(words: list[str], plain: list[str]) -> np.ndarray:
    """Signs of a word that are no letters or digits, up to four of them."""
    return np.clip([(len(w) - len(p)) / 4 for w, p in zip(words, plain)], 0, 1).astype(np.float32)


def _odds_of(odds: np.ndarray, whole: np.ndarray, grams: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Log odds of each word, the strongest and the mean of its n-grams."""
    got = odds[(grams & np.uint64(TABLE - 1)).astype(np.int64)]
    count = np.diff(np.append(start, len(grams)))
    return np.stack((odds[(whole & np.uint64(TABLE - 1)).astype(np.int64)], np.maximum.reduceat(got, start), np.add.reduceat(got, start) / count), axis=1).astype(np.float32) / 3


def _slot(h: np.ndarray) -> np.ndarray:
    return ((h >> np.uint64(40)) % np.uint64(SLOTS)).astype(np.int64)


@dataclass
class Network:
    odds: np.ndarray  # log odds by hash of a word or n-gram
    weights: dict[str, np.ndarray]
    slope: float = 1.0
    shift: float = 0.0
    table: np.ndarray | None = None  # learned vectors by slot of a word or n-gram

    def inputs(self, words: list[str]) -> np.ndarray:
        """One row of inputs per word."""
        plain = [_plain(w)[:LONGEST] or "\x04" for w in words]
        if not len(words):
            return np.zeros((0, INPUTS), np.float32)
        whole, grams, start = _hashed(plain)
        count = np.diff(np.append(start, len(grams))).astype(np.float32)
        mean = np.add.reduceat(self.table[_slot(grams)], start) / count[:, None]
        return np.hstack((_odds_of(self.odds, whole, grams, start), _marks(words, plain)[:, None], self.table[_slot(whole)], mean))


class Vocabulary(dict):
    """Word to row of projected inputs; rows of new words are made together. Row 0 is padding."""

    def __init__(self, net: Network, limit: int = VOCABULARY):
        super().__init__()
        self.net, self.new, self.limit = net, [], limit
        self.store, self.rows = np.zeros((1024, INPUTS), np.float32), np.zeros((1, INPUTS), np.float32)

    def __missing__(self, word):
        self[word] = at = len(self) + 1
        self.new.append(word)
        return at

    def ids(self, words: list[str]) -> np.ndarray:
        if len(self) > self.limit:
            self.clear()
            self.rows = self.rows[:1]
        at = np.fromiter(map(self.__getitem__, words), np.int64, len(words))
        if self.new:
            n = len(self.rows) + len(self.new)
            if n > len(self.store):
                self.store = np.concatenate((self.rows, np.zeros((n, INPUTS), np.float32)))
            for a, b in slices([len(w) for w in self.new], CHARS):
                self.store[len(self.rows) + a : len(self.rows) + b] = self.net.inputs(self.new[a:b])
            self.rows = self.store[:n]
            self.new = []
        return at


def _sigmoid(x):
    return 1 / (1 + np.exp(-x))


def _direction(x, mask, w, u, b, back: bool, keep: bool):
    """Hidden states of one direction; x: windows x time x 3H already projected."""
    n, steps, _ = x.shape
    h = np.zeros((n, HIDDEN), np.float32)
    out, tape = np.empty((n, steps, HIDDEN), np.float32), []
    for t in reversed(range(steps)) if back else range(steps):
        a = h @ u[:, : 2 * HIDDEN]
        a += x[:, t, : 2 * HIDDEN]
        g = _sigmoid(a)
        z, r = g[:, :HIDDEN], g[:, HIDDEN:]
        rec = h @ u[:, 2 * HIDDEN :]
        c = np.tanh(x[:, t, 2 * HIDDEN :] + r * rec)
        m = mask[:, t, None]
        new = np.where(m, h + z * (c - h), h)
        if keep:
            tape.append((t, h, z, r, c, rec, m))
        h = new
        out[:, t] = h
    return out, tape


def project(net: Network, rows: np.ndarray) -> dict[str, np.ndarray]:
    """Input parts of all gates for every row of the table, per direction."""
    return {d: rows @ net.weights["w" + d] + net.weights["c" + d] for d in "fb"}


def forward(net: Network, rows: np.ndarray, idx: np.ndarray, keep: bool = False, projected: dict | None = None):
    """Logits of windows; idx: windows x WINDOW rows of ``rows`` (0: padding)."""
    w, mask = net.weights, idx > 0
    xs, hs, tapes = [], [], []
    for d in ("f", "b"):
        x = (projected or project(net, rows))[d][idx]
        h, tape = _direction(x, mask, w["w" + d], w["u" + d], w["c" + d], d == "b", keep)
        hs.append(h)
        tapes.append(tape)
    h = np.concatenate(hs, axis=2)
    e = np.where(mask, h @ w["a"], -1e9)
    e = np.exp(e - e.max(axis=1, keepdims=True)) * mask
    alpha = e / np.maximum(e.sum(axis=1, keepdims=True), 1e-9)
    pooled = np.einsum("nt,nth->nh", alpha, h)
    logit = pooled @ w["o"] + w["k"][0]
    return logit, (idx, mask, h, alpha, pooled, tapes)


def backward(net: Network, rows: np.ndarray, tape, dlogit: np.ndarray) -> dict[str, np.ndarray]:
    """Gradients of all weights for d loss / d logit."""
    w, (idx, mask, h, alpha, pooled, tapes) = net.weights, tape
    grad = {k: np.zeros_like(v) for k, v in w.items()}
    grad["rows"] = np.zeros_like(rows)  # what the inputs learn
    grad["o"] += pooled.T @ dlogit
    grad["k"][0] += dlogit.sum()
    dpool = dlogit[:, None] * w["o"][None]
    dalpha = np.einsum("nh,nth->nt", dpool, h)
    de = alpha * (dalpha - (alpha * dalpha).sum(axis=1, keepdims=True))
    grad["a"] += np.einsum("nt,nth->h", de, h)
    dh = alpha[:, :, None] * dpool[:, None] + de[:, :, None] * w["a"]
    for k, d in enumerate(("f", "b")):
        u, own, dnext = w["u" + d], dh[:, :, k * HIDDEN : (k + 1) * HIDDEN], 0.0
        for t, h0, z, r, c, rec, m in reversed(tapes[k]):
            dt = own[:, t] + dnext
            live = np.where(m, dt, 0)
            dz, dc = live * (c - h0) * z * (1 - z), live * z * (1 - c * c)
            dr = dc * rec * r * (1 - r)
            da = np.concatenate((dz, dr), axis=1)
            dx = np.concatenate((da, dc), axis=1)
            grad["u" + d][:, : 2 * HIDDEN] += h0.T @ da
            grad["u" + d][:, 2 * HIDDEN :] += h0.T @ (dc * r)
            grad["w" + d] += rows[idx[:, t]].T @ dx
            grad["c" + d] += dx.sum(axis=0)
            np.add.at(grad["rows"], idx[:, t], dx @ w["w" + d].T)
            dnext = np.where(m, dt * (1 - z), dt) + da @ u[:, : 2 * HIDDEN].T + (dc * r) @ u[:, 2 * HIDDEN :].T
    return grad


def windows(sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For texts of so many words laid end to end: rows of word positions (-1: none), and the text of each row."""
    count = np.maximum(1, -(-(np.maximum(sizes - WINDOW, 0)) // STRIDE) + 1) * (sizes > 0)
    text = np.repeat(np.arange(len(sizes)), count)
    nth = np.arange(len(text)) - np.repeat(np.cumsum(count) - count, count)
    at = nth[:, None] * STRIDE + np.arange(WINDOW)
    return np.where(at < sizes[text][:, None], at + (np.cumsum(sizes) - sizes)[text][:, None], -1), text


def strongest(net: Network, vocab: Vocabulary, texts: list[list[str]]) -> tuple[np.ndarray, np.ndarray]:
    """Highest window logit of each text (-inf: no words) and the number of its windows."""
    best, many = np.full(len(texts), -np.inf), np.zeros(len(texts), np.int64)
    for a, b in slices([len(t) for t in texts], TOKENS):
        sizes = np.array([len(t) for t in texts[a:b]])
        ids = np.concatenate((vocab.ids([w for t in texts[a:b] for w in t]), [0]))
        at, text = windows(sizes)
        projected = project(net, vocab.rows)
        for lo in range(0, len(at), AT_ONCE):
            logit, _ = forward(net, vocab.rows, ids[at[lo : lo + AT_ONCE]], projected=projected)
            np.maximum.at(best, a + text[lo : lo + AT_ONCE], logit)
        many[a:b] = np.bincount(text, minlength=b - a)
    return best, many


def _logits(net: Network, rows: np.ndarray, idx: np.ndarray) -> np.ndarray:
    projected = project(net, rows)
    return np.concatenate([forward(net, rows, idx[i : i + AT_ONCE], projected=projected)[0] for i in range(0, len(idx), AT_ONCE)])


def _log_odds(seen: np.ndarray, texts: np.ndarray) -> np.ndarray:
    """Smoothed log odds of the toxic class per slot, shrunk where few texts have it; counts by class of the texts that hold a slot, and of all."""
    both = seen[0] + seen[1]
    odds = np.log((seen[1] + 1) / (texts[1] + 2)) - np.log((seen[0] + 1) / (texts[0] + 2))
    return (odds * both / (both + 4)).astype(np.float32)


def _calibrated(top: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and shift of a logistic curve through logits, with a mild pull to the raw logit."""
    a, b = 1.0, 0.0
    for _ in range(400):
        p = _sigmoid(np.clip(a * top + b, -30, 30))
        a -= 0.5 * (np.mean((p - y) * top) / max(1.0, float(np.mean(top * top))) + 1e-3 * (a - 1))
        b -= 0.5 * float(np.mean(p - y))
    return max(a, 0.05), b


def fit(texts: list[str], labels: np.ndarray, seed: int = 5, least_epochs: int = 10, least_steps: int = 500) -> Network:
    """The network for labelled texts (0 or 1), both classes present."""
    rng = np.random.default_rng(seed)
    part = np.zeros(len(texts), np.int64)
    for y in (0, 1):  # every class dealt evenly: part -1 calibrates, if both classes have texts for it
        mine = rng.permutation(np.flatnonzero(labels == y))
        part[mine] = np.arange(len(mine)) % PARTS
        if min(labels.sum(), (1 - labels).sum()) >= 4 * HELD:
            part[mine[::HELD]] = -1
    learn = np.flatnonzero(part >= 0)
    code: dict[str, int] = {}
    ids = {i: np.array([code.setdefault(w, len(code) + 1) for w in words_of(texts[i])], np.int32) for i in learn.tolist()}
    words = list(code)
    del code
    plain = [_plain(w)[:LONGEST] or "\x04" for w in words]
    whole, grams, start = _hashed(plain)
    ends = np.append(start, len(grams))
    count = np.diff(ends)
    slot_of = lambda h: (h & np.uint64(TABLE - 1)).astype(np.int32)
    word_at, gram_at = slot_of(whole), slot_of(grams)
    seen, many = np.zeros((PARTS, 2, TABLE), np.float32), np.zeros((PARTS, 2))
    for i in learn.tolist():
        own = np.unique(ids[i]).astype(np.int64) - 1
        at = np.unique(np.concatenate([word_at[own], *(gram_at[ends[k] : ends[k + 1]] for k in own.tolist())]))
        seen[part[i], labels[i], at] += 1
        many[part[i], labels[i]] += 1
    every, all_of = seen.sum(axis=0), many.sum(axis=0)
    foreign = np.concatenate([_odds_of(_log_odds(every - seen[k], all_of - many[k]), whole, grams, start) for k in range(PARTS)])  # part after part
    odds = _log_odds(every, all_of)
    del seen, every
    marks, v = _marks(words, plain)[:, None], len(words)
    del words
    normal = lambda *s: (rng.normal(size=s) * 0.3).astype(np.float32)
    weights = {"o": normal(2 * HIDDEN), "a": normal(2 * HIDDEN), "k": np.zeros(1, np.float32)}
    for d in ("f", "b"):
        weights |= {"w" + d: normal(INPUTS, 3 * HIDDEN), "u" + d: normal(HIDDEN, 3 * HIDDEN), "c" + d: np.zeros(3 * HIDDEN, np.float32)}
    net = Network(odds, weights, table=normal(SLOTS, VECTOR))
    own_slot, gram_slot = _slot(whole).astype(np.int32), _slot(grams).astype(np.int32)
    del whole, grams, word_at, gram_at, plain

    def gathered(k: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """n-gram numbers of words k, and where each word's begin."""
        first = np.cumsum(count[k]) - count[k]
        return np.arange(count[k].sum()) - np.repeat(first - start[k], count[k]), first

    def vectors_of(k: np.ndarray) -> np.ndarray:
        """Learned inputs of words k."""
        at, first = gathered(k)
        return np.hstack((net.table[own_slot[k]], np.add.reduceat(net.table[gram_slot[at]], first) / count[k][:, None])).astype(np.float32)

    def rows_of(seen: np.ndarray) -> np.ndarray:
        """Inputs of words as a part of the sample sees them: row 1 + part * words + word."""
        k = (seen - 1) % v
        return np.hstack((foreign[seen - 1], marks[k], vectors_of(k)))

    def window_scores() -> np.ndarray:
        """Logits of all windows, part by part, so that one part's inputs are held at a time."""
        out, rows = np.empty(len(idx), np.float32), np.zeros((1 + v, INPUTS), np.float32)
        rows[1:, 3] = marks[:, 0]
        for lo in range(0, v, 4096):  # words in short runs
            k = np.arange(lo, min(v, lo + 4096))
            rows[1 + k, 4:] = vectors_of(k)
        for p in range(PARTS):
            mine = np.flatnonzero(part[text] == p)
            if len(mine):
                rows[1:, :3] = foreign[p * v : (p + 1) * v]
                out[mine] = _logits(net, rows, np.where(idx[mine] > 0, idx[mine] - p * v, 0))
        return out

    idx, text = [], []
    for i in learn.tolist():
        at, _ = windows(np.array([len(ids[i])]))
        idx.append(np.append(ids[i] + np.int32(part[i] * v), np.int32(0))[at])
        text += [i] * len(at)
    del ids
    idx, text = np.concatenate(idx), np.array(text)
    first = np.searchsorted(text, np.unique(text))
    y_of = labels[text[first]]
    bounds = np.append(first, len(text))
    pad = np.zeros((1, INPUTS), np.float32)
    score = np.concatenate((np.zeros(1, np.float32), foreign[:, 1]))[idx].max(axis=1)
    m = {k: (np.zeros_like(w), np.zeros_like(w)) for k, w in weights.items()}
    power, step = np.full_like(net.table, 1e-6), 0
    batches = max(1, (len(first) + int((y_of == 0).sum())) // 96)
    epochs = max(least_epochs, -(-least_steps // batches))
    for epoch in range(epochs):
        if epoch and epoch % max(3, epochs // 4) == 0:
            score = window_scores()
        chosen = np.array([a + int(score[a:b].argmax()) for a, b in zip(bounds[:-1], bounds[1:])])
        extra = rng.integers(bounds[:-1], bounds[1:])[y_of == 0]
        use, y = np.concatenate((chosen, extra)), np.concatenate((y_of, np.zeros(len(extra))))
        for some in np.array_split(rng.permutation(len(use)), batches):
            seen, own = np.unique(idx[use[some]], return_inverse=True)  # only the rows that the batch has
            own = own.reshape(idx[use[some]].shape)
            if seen[0] == 0:  # row 0 stays padding
                seen = seen[1:]
            else:
                own = own + 1
            few = np.vstack((pad, rows_of(seen)))
            logit, tape = forward(net, few, own, keep=True)
            grad = backward(net, few, tape, ((_sigmoid(logit) - y[some]) / len(some)).astype(np.float32))
            step += 1
            for k in weights:
                m1, m2 = m[k]
                m1 += 0.1 * (grad[k] - m1)
                m2 += 0.001 * (grad[k] * grad[k] - m2)
                weights[k] -= (0.01 * (m1 / (1 - 0.9**step)) / (np.sqrt(m2 / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
            k, d = (seen - 1) % v, grad["rows"][1:]
            at, _ = gathered(k)
            dt = np.zeros_like(net.table)
            np.add.at(dt, own_slot[k], d[:, 4 : 4 + VECTOR])
            np.add.at(dt, gram_slot[at], np.repeat(d[:, 4 + VECTOR :] / count[k][:, None], count[k], axis=0))
            power += dt * dt
            net.table -= 0.02 * dt / np.sqrt(power)
    judge = np.flatnonzero(part < 0) if (part < 0).any() else learn
    top, vocab = np.empty(len(judge)), Vocabulary(net)
    for lo in range(0, len(judge), 64):
        top[lo : lo + 64] = strongest(net, vocab, [words_of(texts[i]) for i in judge[lo : lo + 64].tolist()])[0]
    net.slope, net.shift = _calibrated(np.maximum(top, -30.0), labels[judge])
    return net


def sample(docs: DataFrame, labels: DataFrame, folds: int, held: int) -> tuple[list[str], np.ndarray, float]:
    """Texts and labels of the bounded training sample, and the log odds of toxic in all training labels less those in the sample's."""
    rows = labels.filter(F.col("toxic").isin(0, 1) & (fold("doc_id", folds) != held)).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("y"))
    many = {r["y"]: r["count"] for r in rows.groupBy("y").count().collect()}
    key = F.xxhash64(F.lit(3), "doc_id")
    ids = [r for y, n in ((1, POSITIVES), (0, NEGATIVES)) for r in rows.filter(F.col("y") == y).orderBy(key, "doc_id").limit(n).collect()]
    if len(many) < 2:
        return [], np.zeros(0), 0.0
    prior = float(np.log(many[1] / many[0]) - np.log(min(many[1], POSITIVES) / min(many[0], NEGATIVES)))
    wanted = docs.sparkSession.createDataFrame([(r["doc_id"], r["y"]) for r in ids], "doc_id long, y int")
    got = docs.filter(F.length("text") <= TRAIN_CHARS).join(F.broadcast(wanted), "doc_id").select("doc_id", "text", "y").dropDuplicates(["doc_id"]).collect()
    got = sorted((r for r in got if r["text"].split()), key=lambda r: r["doc_id"])
    return [r["text"] for r in got], np.array([r["y"] for r in got]), prior


def train(docs: DataFrame, labels: DataFrame, folds: int = 4, held: int = 2) -> Network | None:
    text_batches(docs.sparkSession)
    texts, y, prior = sample(docs.select("doc_id", "text"), labels.select("doc_id", "toxic"), folds, held)
    if len(y) == 0 or y.min() == y.max():
        return None
    net = fit(texts, y)
    net.shift += prior  # THRESHOLD means the same at every size of the table
    del texts
    trim()
    return net


def scorer(shared):
    def run(batches):
        net: Network = shared.value
        vocab = Vocabulary(net)
        for batch in sliced(batches):
            texts = batch.column("text").to_pylist()
            score, many = np.zeros(len(texts)), np.zeros(len(texts), np.int64)
            if net is not None:
                for a, b in slices([len(t or "") for t in texts], 4 * TOKENS):
                    best, many[a:b] = strongest(net, vocab, [words_of(t) for t in texts[a:b]])
                    score[a:b] = np.where(many[a:b] > 0, _sigmoid(np.clip(net.slope * best + net.shift, -30, 30)), 0.0)
            names = [n for n in batch.schema.names if n != "text"]
            yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in names), pa.array(score), pa.array((score >= THRESHOLD).astype(np.int32)), pa.array(many)], names=[*names, "score", "predicted", "windows"])

    return run


def score(docs: DataFrame, labels: DataFrame, folds: int = 4, held: int = 2) -> DataFrame:
    """doc_id, held_out, score, predicted, windows for every document."""
    shared = docs.sparkSession.sparkContext.broadcast(train(docs, labels, folds, held))  # a fixed table and small matrices
    rows = docs.select("doc_id", (fold("doc_id", folds) == held).alias("held_out"), "text")
    return rows.mapInArrow(scorer(shared), "doc_id long, held_out boolean, score double, predicted int, windows long")


def _passing(shared):
    def run(batches):
        net: Network = shared.value
        vocab = Vocabulary(net)
        for batch in sliced(batches):
            texts = batch.column("text").to_pylist()
            keep = np.ones(len(texts), bool)
            if net is not None:
                for a, b in slices([len(t or "") for t in texts], 4 * TOKENS):
                    best, many = strongest(net, vocab, [words_of(t) for t in texts[a:b]])
                    keep[a:b] = (many == 0) | (_sigmoid(np.clip(net.slope * best + net.shift, -30, 30)) < THRESHOLD)
            yield batch.filter(pa.array(keep))

    return run


def without_toxic(docs: DataFrame, labels: DataFrame, folds: int = 4, held: int = 2) -> DataFrame:
    """``docs`` with all their columns, less the documents predicted toxic."""
    shared = docs.sparkSession.sparkContext.broadcast(train(docs, labels, folds, held))
    return docs.mapInArrow(_passing(shared), docs.schema)
