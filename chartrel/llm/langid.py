"""Language identification by interpolated Kneser-Ney character models.

Letters are lower-cased, every other run of characters becomes one blank. Counts of the highest order cover all training
rows and are summed by Spark; lower orders follow from them, in Spark, as continuation counts. The finished models are one table:
sorted 64-bit n-gram hashes beside a row of log probabilities, one column per language, so one binary search scores a
character in all languages. The language of lowest mean cross-entropy wins; texts whose cross-entropy lies above the
bound of the winner, calibrated on all training rows, are marked ``rejected``.

Defined results: a null text, or one without a letter, is ``und`` with score 0 and is rejected. Ties go to the language
first by code point. Rows of null language or null text are not learned from; repeated rows count as often as they
occur. With no training rows every prediction is ``und``. Extra columns are ignored.

The driver holds the distinct n-grams once, with one number per language each, and broadcasts the finished table: its
memory grows with the languages' distinct n-grams, which no cap cuts, and not with the rows.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, fold, mix, sliced, slices, stored, text_batches

ORDER = 4
BLANK = 32
#: Cells per nat in which cross-entropies and margins of training rows are counted.
CELLS = 4096
CHARS = 1 << 19

_FIRST = 1 << 16
_AHEAD = np.full(ORDER - 1, BLANK, np.uint32)
_lower = None


def _alphabet() -> np.ndarray:
    """Code point to letter (lower case) or blank, for the first plane; built once per process."""
    global _lower
    if _lower is None:
        _lower = np.full(_FIRST, BLANK, dtype=np.uint32)
        for i in range(_FIRST):
            c = chr(i)
            if c.isalpha() and not 0xD800 <= i <= 0xDFFF:
                low = c.lower()
                _lower[i] = ord(low) if len(low) == 1 else i
    return _lower


def letters(text: str) -> np.ndarray:
    """Code points of a text: letters lower-cased, other runs as one blank, one blank behind and ORDER - 1 ahead."""
    raw = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    low = _alphabet()
    codes = low[np.minimum(raw, _FIRST - 1)]
    if raw.size and raw.max() >= _FIRST:
        high = raw >= _FIRST
        codes[high] = [ord(chr(c).lower()[0]) if c < 0x110000 and chr(c).isalpha() else BLANK for c in raw[high].tolist()]
    blank = codes == BLANK
    codes = codes[~(blank & np.concatenate(([True], blank[:-1])))] if codes.size else codes  # the run ahead is given
    if codes.size and codes[-1] == BLANK:
        codes = codes[:-1]
    return np.concatenate((_AHEAD, codes, _AHEAD[:1]))


def gram_hashes(codes: np.ndarray, n: int) -> np.ndarray:
    """Rolling hashes of all n-grams; position i is the gram that ends at character i + n - 1."""
    x = mix(codes)
    k = len(x) - n + 1
    if k <= 0:
        return np.zeros(0, np.uint64)
    with np.errstate(over="ignore"):
        h = np.zeros(k, np.uint64)
        for j in range(n):
            h = h * np.uint64(0x9DDFEA08EB382D69) + x[j : j + k]
    return h ^ (h >> np.uint64(29))


def _joined(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Texts end to end, where each starts, and the characters that the blanks ahead of each text occupy."""
    each = [letters(t) for t in texts]
    starts = np.cumsum([0, *(len(e) for e in each[:-1])])
    return np.concatenate(each), starts, (starts[:, None] + np.arange(ORDER - 1)).ravel()


def _count(batches):
    for batch in sliced(batches, 2048):
        langs, texts = np.array(batch.column("lang").to_pylist(), dtype=object), batch.column("text").to_pylist()
        for lang in sorted(set(langs.tolist())):
            mine = [texts[i] for i in np.flatnonzero(langs == lang)]
            for a, b in slices([len(t) for t in mine], CHARS):
                codes, _, ahead = _joined(mine[a:b])
                ends = np.delete(np.arange(len(codes)), ahead)
                h, first, n = np.unique(gram_hashes(codes, ORDER)[ends - ORDER + 1], return_index=True, return_counts=True)
                whole = codes.astype("<u4").tobytes()
                grams = [whole[4 * (i - ORDER + 1) : 4 * (i + 1)].decode("utf-32-le", "replace") for i in ends[first].tolist()]
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(grams), pa.string()), pa.array(grams, pa.string()), pa.array(n.astype(np.int64))], names=["lang", "gram", "n"])


def count_grams(rows: DataFrame) -> DataFrame:
    """lang, gram, n over all ``rows`` (lang, text)."""
    return rows.filter("lang is not null and text is not null").select("lang", "text").mapInArrow(_count, "lang string, gram string, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))


@dataclass
class KneserNey:
    """Models of all languages in one sorted table: ``logp[i, l]`` of the gram hashed ``keys[i]``."""

    langs: list[str]
    keys: list[np.ndarray]
    logp: list[np.ndarray]
    gamma_keys: list[np.ndarray]
    gamma: list[np.ndarray]
    unit: np.ndarray
    bound: np.ndarray
    scale: float

    def score(self, codes: np.ndarray) -> np.ndarray:
        """Log probability in every language of each character that has ORDER - 1 others before it."""
        h = gram_hashes(codes, ORDER)
        keys = self.keys[ORDER - 1]
        at = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
        out = self.logp[ORDER - 1][at]
        miss = np.flatnonzero(keys[at] != h)
        if len(miss):
            out[miss] = self._back(codes, miss + ORDER - 1, ORDER - 1)
        return out

    def _back(self, pad: np.ndarray, ends: np.ndarray, n: int) -> np.ndarray:
        """Interpolated log probability at ``ends`` when the gram of order n + 1 was never seen in any language."""
        ctx = gram_hashes_at(pad, ends - 1, n)
        keys = self.gamma_keys[n]
        at = np.minimum(np.searchsorted(keys, ctx), len(keys) - 1)
        weight = np.where((keys[at] == ctx)[:, None], self.gamma[n][at], np.float32(0))
        if n == 1:
            h = gram_hashes_at(pad, ends, 1)
            at = np.minimum(np.searchsorted(self.keys[0], h), len(self.keys[0]) - 1)
            low = np.where((self.keys[0][at] == h)[:, None], self.logp[0][at], self.unit)
        else:
            h = gram_hashes_at(pad, ends, n)
            at = np.minimum(np.searchsorted(self.keys[n - 1], h), len(self.keys[n - 1]) - 1)
            low = self.logp[n - 1][at]
            miss = np.flatnonzero(self.keys[n - 1][at] != h)
            if len(miss):
                low[miss] = self._back(pad, ends[miss], n - 1)
        return weight + low


def gram_hashes_at(codes: np.ndarray, ends: np.ndarray, n: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        h = np.zeros(len(ends), np.uint64)
        for j in range(n):
            h = h * np.uint64(0x9DDFEA08EB382D69) + mix(codes[ends - n + 1 + j])
    return h ^ (h >> np.uint64(29))


def _string_hashes(grams: list[str], n: int) -> np.ndarray:
    if not grams:
        return np.zeros(0, np.uint64)
    codes = np.frombuffer("".join(grams).encode("utf-32-le", "surrogatepass"), np.uint32)
    return gram_hashes_at(codes, np.arange(1, len(grams) + 1) * n - 1, n)


def levels_of(grams: DataFrame) -> list[DataFrame]:
    """lang, gram, n of orders 1..ORDER: raw counts at the top, continuation counts (distinct left neighbours) below."""
    out = [grams]
    for n in range(ORDER - 1, 0, -1):
        out.insert(0, out[0].groupBy("lang", F.substring("gram", 2, n).alias("gram")).agg(F.count("*").alias("n")))
    return out


def _levels(counts: dict[str, dict[str, int]]) -> list[tuple[list[str], list[str], list[int]]]:
    """The same of counts in memory: columns lang, gram, n per order."""
    out = [([g for g in counts for _ in counts[g]], [w for g in counts for w in counts[g]], [c for g in counts for c in counts[g].values()])]
    for _ in range(ORDER - 1):
        low: dict[tuple[str, str], int] = {}
        for g, w in zip(*out[0][:2]):
            low[g, w[1:]] = low.get((g, w[1:]), 0) + 1
        out.insert(0, ([g for g, _ in low], [w for _, w in low], list(low.values())))
    return out


def build(counts: dict[str, dict[str, int]]) -> KneserNey:
    """Models from highest-order counts per language."""
    return assembled(_levels(counts))


def assembled(levels) -> KneserNey:
    """Models from columns lang, gram, n of every order, lowest first, in whole arrays."""
    langs = sorted(set(levels[-1][0]), key=lambda s: s.encode("utf-32-be"))
    at = {g: i for i, g in enumerate(langs)}
    alphabet = len(set(levels[0][1])) + 1
    unit = np.zeros(len(langs), np.float32)
    keys, logp, gkeys, gamma, prob = [], [], [np.zeros(1, np.uint64)], [np.zeros((1, len(langs)), np.float32)], None
    for n, (own, grams, count) in enumerate(levels, 1):
        own, count = np.array([at[g] for g in own]), np.asarray(count, np.float64)
        key, first, which = np.unique(_string_hashes(grams, n), return_index=True, return_inverse=True)
        c = np.zeros((len(key), len(langs)))
        c[which, own] = count
        heads = _string_hashes([w[:-1] for w in grams], n - 1) if n > 1 else np.zeros(len(grams), np.uint64)
        ctx, group = np.unique(heads, return_inverse=True)
        tot, kind = np.zeros((2, len(ctx), len(langs)))
        np.add.at(tot, (group, own), count)
        np.add.at(kind, (group, own), 1)
        d = np.full(len(langs), 0.1)
        for l in range(len(langs)):
            ones, twos = (int(((own == l) & (count == k)).sum()) for k in (1, 2))
            d[l] = min(0.95, max(0.1, ones / (ones + 2 * twos))) if ones else 0.1
        weight = np.divide(d * kind, tot, out=np.ones_like(tot), where=tot > 0)  # of the lower order; all of it where the context was never seen
        low = prob[np.searchsorted(keys[-1], _string_hashes([grams[i][1:] for i in first.tolist()], n - 1))] if n > 1 else np.full((1, len(langs)), 1 / alphabet)
        mine = group[first]
        prob = np.divide(np.maximum(c - d, 0), tot[mine], out=np.zeros_like(c), where=tot[mine] > 0) + weight[mine] * low
        keys.append(key)
        logp.append(np.log(prob).astype(np.float32))
        if n == 1:
            unit = np.log(weight[0] / alphabet).astype(np.float32)
        else:
            gkeys.append(ctx)
            gamma.append(np.log(weight).astype(np.float32))
    return KneserNey(langs, keys, logp, gkeys, gamma, unit, np.full(len(langs), np.inf), 1.0)


def entropies(model: KneserNey, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Mean cross-entropy per character and language, and the number of scored characters, of whole texts."""
    out, size = np.zeros((len(texts), len(model.langs))), np.zeros(len(texts))
    for a, b in slices([len(t) for t in texts], CHARS):
        codes, starts, ahead = _joined(texts[a:b])
        size[a:b] = np.diff(np.append(starts, len(codes))) - ORDER + 1
        if len(starts) == 1:
            for lo in range(0, len(codes) - ORDER + 1, CHARS):
                out[a] += model.score(codes[lo : lo + CHARS + ORDER - 1]).sum(axis=0, dtype=np.float64)
            continue
        got = np.vstack((np.zeros((ORDER - 1, len(model.langs))), model.score(codes)))
        got[ahead] = 0
        out[a:b] = np.add.reduceat(got, starts, axis=0)
    return -out / np.maximum(size, 1)[:, None], size


def train(rows: DataFrame, calibration: int | None = None) -> KneserNey | None:
    """Models of all counts over ``rows`` (doc_id, lang, text), calibrated on all of them; ``calibration`` is read no more."""
    rows = rows.filter("lang is not null and text is not null")
    model = _models(rows)
    if model is not None:
        keep = Scratch(rows.sparkSession)
        calibrate(model, keep(scored(rows.withColumn("held_out", F.lit(False)), model), "entropies"))
        keep.clear()
    return model


def _models(rows: DataFrame) -> KneserNey | None:
    """The same without score and rejection."""
    keep = Scratch(rows.sparkSession)
    levels = []
    for level in levels_of(keep(count_grams(rows), "gram-counts")):
        got = level.toArrow()
        levels.append((got.column("lang").to_pylist(), got.column("gram").to_pylist(), got.column("n").to_numpy()))
    keep.clear()
    return assembled(levels) if levels[-1][0] else None


def scored(rows: DataFrame, model: KneserNey | None) -> DataFrame:
    """doc_id, held_out, lang, size and mean cross-entropies in every language (h) of whole texts."""
    shared = rows.sparkSession.sparkContext.broadcast(model)  # grows with the distinct four-grams of the languages, not with rows

    def run(batches):
        for batch in sliced(batches):
            texts = [t or "" for t in batch.column("text").to_pylist()]
            h, size = entropies(shared.value, texts) if shared.value is not None else (np.zeros((len(texts), 0)), np.zeros(len(texts)))
            ends = np.arange(len(texts) + 1, dtype=np.int32) * h.shape[1]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), batch.column("lang"), pa.array(size, pa.float64()), pa.ListArray.from_arrays(pa.array(ends), pa.array(h.ravel(), pa.float64()))], names=["doc_id", "held_out", "lang", "size", "h"])

    return rows.select("doc_id", "held_out", "lang", "text").mapInArrow(run, "doc_id long, held_out boolean, lang string, size double, h array<double>")


def _cells(langs: list[str]):
    at = {g: i for i, g in enumerate(langs)}

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            own = np.array([at[g] for g in batch.column("lang").to_pylist()])
            h = batch.column("h").flatten().to_numpy().reshape(batch.num_rows, len(langs))
            i = np.arange(len(own))
            mine = h[i, own]
            kinds = [(own, mine)]
            if len(langs) > 1:
                rest = h.copy()
                rest[i, own] = np.inf
                kinds.append((np.full(len(own), -1), np.abs(rest.min(axis=1) - mine)))
            for kind, v in kinds:
                pair, n = np.unique(np.stack((kind, np.rint(v * CELLS).astype(np.int64))), axis=1, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(pair[0], pa.int64()), pa.array(pair[1], pa.int64()), pa.array(n, pa.int64())], names=["kind", "cell", "n"])

    return run


def quantile(cells: np.ndarray, n: np.ndarray, q: float) -> float:
    """A quantile, interpolated between neighbours, of values counted in cells (sorted)."""
    ends = np.cumsum(n)
    at = q * (ends[-1] - 1)
    low, high = (cells[np.searchsorted(ends, k, side="right")] / CELLS for k in (np.floor(at), np.ceil(at)))
    return float(low + (high - low) * (at - np.floor(at)))


def calibrate(model: KneserNey, entropy: DataFrame) -> None:
    """Bound of rejection per language and scale of the score from every training row (not held out, of known language, with a letter).

    Values are counted in cells of 1 / CELLS nat in Spark, so the driver gets cells, whose number is bounded by the range of
    cross-entropies and not by rows: at most some ten thousand for each language and as many for the margins.
    """
    rows = entropy.filter("not held_out and lang is not null and size > 1")
    got = rows.select("lang", "h").mapInArrow(_cells(model.langs), "kind long, cell long, n long").groupBy("kind", "cell").agg(F.sum("n").alias("n")).orderBy("kind", "cell").toArrow()
    kind, cell, n = (got.column(c).to_numpy() for c in ("kind", "cell", "n"))
    for l in range(len(model.langs)):
        if (mine := kind == l).any():
            model.bound[l] = quantile(cell[mine], n[mine], 0.995) * 1.25
    margin = quantile(cell[kind == -1], n[kind == -1], 0.5) if (kind == -1).any() else 1.0
    model.scale = 4.0 / max(margin, 1e-6)


def predictor(model: KneserNey | None):
    """Predictions from ``scored`` rows; only names, bounds and scale of the models go along."""
    langs, bound, scale = (model.langs, model.bound, model.scale) if model is not None else ([], None, 1.0)

    def run(batches):
        for batch in batches:
            m = batch.num_rows
            if not m:
                continue
            if not langs:
                lang, score, ce, no = ["und"] * m, np.zeros(m), [None] * m, [True] * m
            else:
                h, size = batch.column("h").flatten().to_numpy().reshape(m, len(langs)), batch.column("size").to_numpy()
                best = h.argmin(axis=1)
                own = h[np.arange(m), best]
                rel = np.exp(-(h - own[:, None]) * scale)
                score = 1 / rel.sum(axis=1)
                none = size <= 1  # only the blank behind: no letter
                lang = ["und" if z else langs[b] for b, z in zip(best.tolist(), none.tolist())]
                score = np.where(none, 0.0, score)
                ce = [None if z else float(v) for v, z in zip(own.tolist(), none.tolist())]
                no = [bool(z or v > bound[b]) for v, z, b in zip(own.tolist(), none.tolist(), best.tolist())]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(ce, pa.float64()), pa.array(no, pa.bool_())], names=["doc_id", "held_out", "lang_pred", "score", "cross_entropy", "rejected"])

    return run


def identify(docs: DataFrame, folds: int = 5) -> DataFrame:
    """Prediction for every document; rows of fold 0 (by hashed id) are held out of training.

    Every text is scored once: the cross-entropies are stored, calibrate on the training rows and become the predictions.
    """
    text_batches(docs.sparkSession)
    rows = docs.select("doc_id", "text", "lang", (fold("doc_id", folds) == 0).alias("held_out"))
    model = _models(rows.filter("not held_out and lang is not null and text is not null"))
    entropy = stored(scored(rows, model), "entropies")
    if model is not None:
        calibrate(model, entropy)
    return entropy.select("doc_id", "held_out", "size", "h").mapInArrow(predictor(model), "doc_id long, held_out boolean, lang_pred string, score double, cross_entropy double, rejected boolean")
