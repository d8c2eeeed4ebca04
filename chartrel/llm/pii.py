"""Personal data in whole texts: fixed base patterns plus a semi-Markov conditional random field.

Base matches are exact and always kept. The field works on runs of blank-delimited pieces that hold a digit or an at
sign: every segment of up to six pieces is scored per type by features of the whole span (shape, checks of digits,
separators, the word before) and by the type of the segment before it, and a bounded-entity dynamic program chooses
boundaries and types together. It reads a run of any length piece by piece and keeps the last six steps' scores only. Elsewhere the
outside label is the only candidate, so leaving those characters out of the program changes nothing. Weights are trained
by conditional likelihood on a bounded sample: TRAIN_RUNS runs of TRAIN_PIECES pieces at most from TRAIN_TEXTS texts of
TRAIN_CHARS characters at most, labelled by the base patterns, by key and password forms, and by variants of base entities
in other spellings. All texts of any length are searched whole.

Defined results: a null text is treated as empty and has no spans. Spans are code points, end exclusive. A span of the
field that touches a base span is left out. Repeated rows are scanned each. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
import random
import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import hashed_sample, sliced, text_batches

KINDS = ("email", "ip", "card", "phone")
TYPES = (*KINDS, "secret")
#: Pieces of one entity at most, characters of one entity at most.
MAX_PIECES, MAX_CHARS = 6, 200
#: Texts that training samples, and runs that it learns from.
TRAIN_TEXTS, TRAIN_RUNS, TRAIN_CHARS, TRAIN_PIECES = 3000, 2500, 20_000, 24
HASHED = 4096

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
_CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_TRIGGER = re.compile(r"[0-9@]")
_GAP = re.compile(r"[\x20\x09-\x0D]")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if i % 2 == 0 else (d * 2 if d < 5 else d * 2 - 9)
    return total % 10 == 0


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost matches found from their at signs, so that long runs cost linear time."""
    out, end, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > end and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at + 1)):
            out.append((start, m.end()))
            end = m.end()
        at = text.find("@", max(at + 1, end))
        end = max(end, 0)
    return out


def base(text: str) -> dict[str, list[tuple[int, int]]]:
    """Base spans by kind."""
    found = {k: [] for k in KINDS}
    if "@" in text:
        found["email"] = emails(text)
    found["ip"] = [m.span() for m in _IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m[0].split("."))]
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 14 and 14 <= len(d := m[0].replace(" ", "").replace("-", "")) <= 19 and luhn(d):
            found["card"].append(m.span())
    if "+" in text:
        found["phone"] = [m.span() for m in _PHONE.finditer(text) if 10 <= sum(c.isdigit() for c in m[0]) <= 15]
    return found


def runs(text: str) -> list[tuple[str, list[tuple[int, int]]]]:
    """Runs of neighbouring pieces with a digit or at sign, each with the piece before it as context."""
    out, pieces, last, n, pos = [], [], 0, len(text), 0
    before = ""
    while m := _TRIGGER.search(text, pos):
        i = m.start()
        lo = max(text.rfind(c, last, i) for c in " \n\t\r\x0b\x0c") + 1
        lo = max(lo, last)
        gap = _GAP.search(text, i)
        hi = gap.start() if gap else n
        if pieces and not (lo - pieces[-1][1] == 1 and text[pieces[-1][1]] == " "):
            out.append((before, pieces))
            pieces = []
        if not pieces:
            before = text[max(0, lo - 40) : lo].strip().rpartition(" ")[2].lower()
            back = text[max(0, lo - 12) : lo].rstrip()
            if back.endswith(("=", ":")):
                before = back.rstrip(" =:").rpartition(" ")[2].lower() + "="
        pieces.append((lo, hi))
        last = pos = hi
    if pieces:
        out.append((before, pieces))
    return out


def trimmed(text: str, lo: int, hi: int) -> tuple[int, int]:
    """A span without quotes and closing marks around it."""
    while lo < hi and text[lo] in "\"'<[{,;:":
        lo += 1
    while hi > lo and text[hi - 1] in "\"'>]},;:.!?":
        hi -= 1
    if hi > lo and text[hi - 1] == ")" and "(" not in text[lo:hi]:
        hi -= 1
    return lo, hi


def _bucket(n: int) -> int:
    return n if n < 6 else 6 + min(10, (n - 6) // 2)


def features(span: str, before: str, pieces: int) -> list[int]:
    """Hashed features of a whole candidate span."""
    digits = "".join(c for c in span if "0" <= c <= "9")
    letters = sum(c.isalpha() for c in span)
    upper = sum("A" <= c <= "Z" for c in span)
    hexa = sum(c in "0123456789abcdefABCDEF" for c in span)
    shape = re.sub(r"(.)\1+", r"\1", re.sub(r"[0-9]+", "9", re.sub(r"[a-z]+", "a", re.sub(r"[A-Z]+", "A", span))))[:16]
    f = [f"n{pieces}", f"d{_bucket(len(digits))}", f"l{_bucket(len(span))}", f"s{shape}", f"c{before}", f"lead{span[:1] if not span[:1].isalnum() else 'x'}"]
    if "@" in span:
        f.append("at1" if span.count("@") == 1 and _DOMAIN.search(span.partition("@")[2]) else "at0")
    if not letters and digits:
        f.append("plain" + "".join(sorted({c for c in span if not c.isdigit()})))
        if 14 <= len(digits) <= 19:
            f.append(f"luhn{luhn(digits)}")
        if 10 <= len(digits) <= 15:
            f.append("phonelen" + ("+" if span[:1] == "+" else ""))
        if span.count(".") == 3:
            f.append(f"quad{all(p.isdigit() and len(p) <= 3 and int(p) <= 255 for p in span.split('.'))}")
    if letters and digits:
        f.append(f"mixed{_bucket(len(span))}u{upper > 4}h{hexa * 5 >= len(span) * 4}")
        if "=" in span or ":" in span:
            f.append("keyed" + re.split("[=:]", span)[0].lower()[:12])
        if upper + len(digits) == len(span) and len(span) >= 12:
            f.append("capkey")
    return [zlib.crc32(x.encode("utf-8", "replace")) % HASHED for x in f]


class SemiMarkov:
    """Weights per type over hashed span features and between neighbouring segments' types; outside pieces are segments of one piece."""

    def __init__(self):
        self.w = np.zeros((len(TYPES) + 1, HASHED))  # the last row is the outside label
        self.t = np.zeros((len(TYPES) + 2, len(TYPES) + 1))  # type before (the last row: none) by type

    def segment(self, text: str, before: str, pieces: list[tuple[int, int]], i: int, j: int) -> tuple[list[int], tuple[int, int]] | None:
        """Features and trimmed span of pieces i to j; None if that is no candidate."""
        lo, hi = trimmed(text, pieces[i][0], pieces[j - 1][1])
        if j - i > 1 and hi - lo > MAX_CHARS:
            return None
        return features(text[lo : min(hi, lo + MAX_CHARS + 1)], before if i == 0 else "9", j - i), (lo, hi)

    def lattice(self, text: str, before: str, pieces: list[tuple[int, int]]) -> dict[tuple[int, int], tuple[list[int], tuple[int, int]]]:
        cells = ((i, j) for j in range(1, len(pieces) + 1) for i in range(max(0, j - MAX_PIECES), j))
        return {(i, j): s for i, j in cells if (s := self.segment(text, before, pieces, i, j))}

    def score(self, i: int, j: int, segment) -> np.ndarray:
        """Score of every type of one segment; the outside label only for single pieces."""
        f, (lo, hi) = segment
        s = self.w[:, f].sum(axis=1)
        if j - i > 1:
            s[-1] = -np.inf
        if hi - lo > MAX_CHARS or hi <= lo:
            s[:-1] = -np.inf
        return s

    def best(self, text: str, before: str, pieces: list[tuple[int, int]]) -> list[tuple[int, int, int, tuple[int, int]]]:
        """Segments (from, to, type, span) of the highest-scoring path; ties go to the shorter last segment, then to the earlier type."""
        ready = {0: self.t[-1].copy()}  # step -> for each type, the best score of a path up to there whose next segment has it
        last: dict[int, tuple] = {}  # step -> per type: where its segment begins, the type before it, its span
        come: list[tuple] = [()]
        for j in range(1, len(pieces) + 1):
            top, here = np.full(len(TYPES) + 1, -np.inf), [None] * (len(TYPES) + 1)
            for i in range(j - 1, max(0, j - MAX_PIECES) - 1, -1):
                if segment := self.segment(text, before, pieces, i, j):
                    s = self.score(i, j, segment) + ready[i]
                    for y in np.flatnonzero(s > top).tolist():
                        top[y], here[y] = s[y], (i, segment[1])
            ready.pop(j - MAX_PIECES, None)
            way = top[:, None] + self.t[:-1]
            ready[j] = way.max(axis=0)
            last[j] = (int(top.argmax()),)
            come.append((tuple(here), tuple(way.argmax(axis=0).tolist())))
        path, j = [], len(pieces)
        y = last[j][0] if j else 0
        while j:
            i, span = come[j][0][y]
            path.append((i, j, y, span))
            y = come[i][1][y] if i else 0
            j = i
        return path[::-1]

    def update(self, n: int, lattice, gold: list[tuple[int, int, int]], rate: float) -> None:
        """One step up the conditional log likelihood: features and type pairs of the gold path less their expectation."""
        score = {k: self.score(*k, v) for k, v in lattice.items()}
        kinds = len(TYPES) + 1
        ahead, behind = np.full((n + 1, kinds), -np.inf), np.full((n + 1, kinds), -np.inf)  # by type of the segment that starts, ends there
        ahead[0], behind[n] = self.t[-1], 0.0
        alpha = np.full((n + 1, kinds), -np.inf)
        with np.errstate(invalid="ignore", divide="ignore"):
            for j in range(1, n + 1):
                parts = [ahead[i] + score[i, j] for i in range(max(0, j - MAX_PIECES), j) if (i, j) in score]
                alpha[j] = np.logaddexp.reduce(parts, axis=0)
                ahead[j] = np.logaddexp.reduce(alpha[j][:, None] + self.t[:-1], axis=0)
            total = np.logaddexp.reduce(alpha[n])
            start = np.full((n + 1, kinds), -np.inf)  # log weight of all that follows from a segment of that type starting there
            for i in range(n - 1, -1, -1):
                start[i] = np.logaddexp.reduce([score[i, j] + behind[j] for j in range(i + 1, min(n, i + MAX_PIECES) + 1) if (i, j) in score], axis=0)
                if i:
                    behind[i] = np.logaddexp.reduce(self.t[:-1] + start[i][None], axis=1)
            for (i, j), s in score.items():
                p = np.exp(ahead[i] + s + behind[j] - total)
                np.subtract.at(self.w, (slice(None), lattice[i, j][0]), rate * p[:, None])
            pairs = np.zeros_like(self.t)
            for i in range(1, n):
                pairs[:-1] += np.exp(alpha[i][:, None] + self.t[:-1] + start[i][None] - total)
            pairs[-1] = np.exp(self.t[-1] + start[0] - total)
        past = len(TYPES) + 1
        for i, j, y in gold:
            np.add.at(self.w, (y, lattice[i, j][0]), rate)
            pairs[past, y] -= 1
            past = y
        self.t -= rate * pairs


_SECRET = re.compile(r"""(?:\b(?:password|passwd|pwd|secret|token|api_?key)\s?[=:]\s?)["']?(?=[^\s"']*[0-9])[A-Za-z0-9_/+.-]{8,}["']?|\b[A-Z]{4}[A-Z0-9]{16}\b""")


def _gold(text: str, pieces, spans: list[tuple[int, int, int]]) -> list[tuple[int, int, int]] | None:
    path, i = [], 0
    while i < len(pieces):
        hit = None
        for lo, hi, y in spans:
            if pieces[i][0] <= lo < pieces[i][1] or lo < pieces[i][0] < hi:
                j = i + 1
                while j < len(pieces) and pieces[j][0] < hi:
                    j += 1
                hit = (i, j, y)
                break
        if hit and hit[1] - i > MAX_PIECES:
            return None
        path.append(hit or (i, i + 1, len(TYPES)))
        i = path[-1][1]
    return path


def _variants(rng: random.Random, n: int) -> list[tuple[str, list[tuple[int, int, int]]]]:
    """Entities in spellings that the base patterns miss, and numbers that are none, in short frames."""
    out, digit = [], lambda k: "".join(rng.choice("0123456789") for _ in range(k))
    for k in range(n):
        kind = k % 7
        y = 3
        if kind == 0:
            x = f"({digit(3)}) {digit(3)}-{digit(4)}"
        elif kind == 1:
            x = f"{digit(3)}-{digit(3)}-{digit(4)}"
        elif kind == 2:
            x, y = f"user{digit(2)}@host{digit(1)}", 0
        elif kind == 3:
            d = [rng.randrange(10) for _ in range(15)]
            d.append(next(c for c in range(10) if luhn("".join(map(str, [*d, c])))))
            s = "".join(map(str, d))
            x, y = f"{s[:4]}.{s[4:8]}.{s[8:12]}.{s[12:]}", 2
        elif kind == 4:
            x, y = "".join(rng.choice("0123456789abcdef") for _ in range(40)), 4
        elif kind == 5:
            x, y = rng.choice((digit(4), digit(2), f"{digit(1)}.{digit(1)}", f"{digit(1)},{digit(3)}", f"{digit(4)}-{digit(2)}-{digit(2)}", f"v{digit(1)}.{digit(2)}")), -1
        else:
            x, y = "".join(rng.choice("ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789") for _ in range(19)) + digit(1), 4
        out.append((f"w {x} w", [(2, 2 + len(x), y)] if y >= 0 else []))
    return out


def fit(texts: list[str], seed: int = 3, epochs: int = 4, most: int = TRAIN_RUNS) -> SemiMarkov:
    """A field trained on silver labels of the given texts and on made-up variants."""
    rng, field, data = random.Random(seed), SemiMarkov(), []
    cases = [(t, [(lo, hi, KINDS.index(k)) for k, s in base(t).items() for lo, hi in s] + [(*m.span(), 4) for m in _SECRET.finditer(t)]) for t in texts]
    for t, spans in cases + _variants(rng, 420):
        spans.sort()
        for before, pieces in runs(t):
            if len(data) < most + 420 and len(pieces) <= TRAIN_PIECES and (gold := _gold(t, pieces, spans)):
                lattice = field.lattice(t, before, pieces)
                if all((i, j) in lattice for i, j, _ in gold):
                    data.append((len(pieces), lattice, gold))
    for epoch in range(epochs):
        rng.shuffle(data)
        for n, lattice, gold in data:
            field.update(n, lattice, gold, 0.2 / (1 + epoch))
    return field


def train(docs: DataFrame) -> SemiMarkov:
    """The field for a bounded sample of texts that hold a digit or at sign, by hashed id."""
    text_batches(docs.sparkSession)
    rows = docs.select("doc_id", "text").filter(F.col("text").rlike("[0-9@]") & (F.length("text") <= TRAIN_CHARS))
    return fit(sorted(r["text"] for r in hashed_sample(rows, TRAIN_TEXTS, "doc_id", "text", salt=1).select("text").collect()))


def find(text: str, field: SemiMarkov) -> tuple[dict[str, list[tuple[int, int]]], list[tuple[int, int, str]]]:
    """Base spans by kind, and all spans (base and field) by start."""
    if not _TRIGGER.search(text):
        return {k: [] for k in KINDS}, []
    own = base(text)
    taken = sorted((lo, hi) for s in own.values() for lo, hi in s)
    starts = [lo for lo, _ in taken]
    reach = np.maximum.accumulate([hi for _, hi in taken]).tolist() if taken else []
    found = [(lo, hi, k) for k, s in own.items() for lo, hi in s]
    for before, pieces in runs(text):
        for _, _, y, (lo, hi) in field.best(text, before, pieces):
            if y < len(TYPES):
                at = int(np.searchsorted(starts, hi))
                if not at or reach[at - 1] <= lo:
                    found.append((lo, hi, TYPES[y]))
    rank = {k: i for i, k in enumerate(TYPES)}
    return own, sorted(found, key=lambda s: (s[0], rank[s[2]], s[1]))


def finder(shared):
    def run(batches):
        field: SemiMarkov = shared.value
        for batch in sliced(batches):
            count, sha, spans, secrets, every = {k: [] for k in KINDS}, [], [], [], []
            for text in batch.column("text").to_pylist():
                own, found = find(text or "", field)
                for k in KINDS:
                    count[k].append(len(own[k]))
                line = ",".join(f"{k}:{lo}:{hi}" for lo, _, k, hi in sorted((lo, i, k, hi) for i, k in enumerate(KINDS) for lo, hi in own[k]))
                sha.append(hashlib.sha256(line.encode()).hexdigest())
                spans.append(",".join(f"{k}:{lo}:{hi}" for lo, hi, k in found))
                secrets.append(sum(k == "secret" for _, _, k in found))
                every.append(len(found))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(count[k], pa.int64()) for k in KINDS), pa.array(sha, pa.string()), pa.array(spans, pa.string()), pa.array(secrets, pa.int64()), pa.array(every, pa.int64())], names=["doc_id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans", "n_secret", "n_all"])

    return run


def personal_data(docs: DataFrame) -> DataFrame:
    """doc_id, base counts, digest of the base spans, all spans and how many are secrets and in all, for every document."""
    shared = docs.sparkSession.sparkContext.broadcast(train(docs))  # a matrix of fixed size
    return docs.select("doc_id", "text").mapInArrow(finder(shared), "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_secret long, n_all long")
