"""Operators against brute force, exact counts and held-out labels."""

import re
import zlib
from collections import Counter
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from chartrel.llm import common, decontam, embeddup, langid, linededup, minhash, mixing, pii, quality, queries, tokencounts, toxicity
from chartrel.llm.common import table
from chartrel.llm.components import components

from .conftest import frame


def docs(spark, d):
    return table(spark, d, "documents")


def test_components_equal_union_find(spark):
    rng = np.random.default_rng(2)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 120, (90, 2))] + [(200, i) for i in range(300, 340)]
    parent = {}

    def root(v):
        while parent.setdefault(v, v) != v:
            v = parent[v]
        return v

    for a, b in edges:
        a, b = root(a), root(b)
        parent[max(a, b)] = min(a, b)
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {v: root(v) for v in parent if any(v in e and e[0] != e[1] for e in edges)}


BASE = {
    "email": re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), "ip": re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"),
    "card": re.compile(r"[0-9]([\x20-]?[0-9])+"), "phone": re.compile(r"\+[0-9][\x20().0-9-]+[0-9]"),
}


def plain_base(text):
    digits = lambda m: re.sub(r"[^0-9]", "", m[0])
    ok = {
        "email": lambda m: True, "ip": lambda m: all(int(p) <= 255 for p in m[0].split(".")),
        "card": lambda m: 14 <= len(digits(m)) <= 19 and pii.luhn(digits(m)), "phone": lambda m: 10 <= len(digits(m)) <= 15,
    }
    return {k: [m.span() for m in r.finditer(text) if ok[k](m)] for k, r in BASE.items()}


def test_pii_base_equals_patterns(spark, mid):
    rng = np.random.default_rng(4)
    texts = [r["text"] for r in docs(spark, mid).collect()]
    texts += ["".join(rng.choice(list("a1@..+-( )%2 5"), rng.integers(1, 45))) for _ in range(8000)]
    texts += ["4041 8949 7460 8795", "+1 (988) 555-2485", "a@b@c.d", "1.2.3.4.5.6.7.8", "999.1.1.1", "x@y", "a.b@c-d.e.f."]
    assert all(pii.base(t) == plain_base(t) for t in texts)


def test_pii_query(spark, mid):
    import hashlib

    got = {r["doc_id"]: r for r in queries.op1_personal_data(spark, mid).collect()}
    for r in docs(spark, mid).collect():
        b, g = plain_base(r["text"]), got[r["doc_id"]]
        line = ",".join(f"{k}:{lo}:{hi}" for lo, _, k, hi in sorted((lo, i, k, hi) for i, k in enumerate(BASE) for lo, hi in b[k]))
        assert g["base_sha256"] == hashlib.sha256(line.encode()).hexdigest() and [g[f"n_{k}"] for k in BASE] == [len(b[k]) for k in BASE]
        assert {x for x in line.split(",") if x} <= set(g["spans"].split(","))


def test_semi_markov_best_path_and_gradient():
    import itertools

    field = pii.fit(["call +1 (212) 555-0199 or mail a.b@c.de, ip 10.0.0.1 card 4041894974608795"] * 3)
    field.t += np.random.default_rng(0).normal(size=field.t.shape)
    text = "to 212 555 0199 77 now"
    (before, pieces), = pii.runs(text)
    lattice, n, kinds = field.lattice(text, before, pieces), len(pieces), len(pii.TYPES) + 1
    cuts = [[0, *c, n] for k in range(n) for c in itertools.combinations(range(1, n), k)]
    paths = [[(a, b, y) for a, b, y in zip(ends, ends[1:], ys)] for ends in cuts for ys in itertools.product(range(kinds), repeat=len(ends) - 1)]

    def totals(some):
        score = {k: field.score(*k, v) for k, v in lattice.items()}
        return [sum(field.t[past, y] + score[i, j][y] for past, (i, j, y) in zip([kinds, *(p[2] for p in path)], path)) for path in some]

    assert totals([[p[:3] for p in field.best(text, before, pieces)]])[0] == pytest.approx(max(totals(paths)))
    gold = [(0, 3, 3), (3, 4, kinds - 1)]
    like = lambda: totals([gold])[0] - np.logaddexp.reduce(totals(paths))
    w, t = field.w.copy(), field.t.copy()
    field.update(n, lattice, gold, 1.0)
    dw, dt = field.w - w, field.t - t
    field.w, field.t = w, t
    most = lambda g: np.unravel_index(int(np.abs(g).argmax()), g.shape)
    for grad, own, at in ((dt, t, most(dt)), (dw, w, most(dw)), (dt, t, (3, kinds - 1)), (dt, t, (kinds, 3))):
        old = own[at]
        own[at] = old + 1e-4
        up = like()
        own[at] = old - 1e-4
        down = like()
        own[at] = old
        assert grad[at] == pytest.approx((up - down) / 2e-4, abs=1e-4)


def test_semi_markov_reads_long_runs_and_finds_more_than_patterns(spark, mid):
    field = pii.fit([r["text"] for r in docs(spark, mid).limit(300).collect()])
    spans = lambda t: [(t[lo:hi], k) for lo, hi, k in pii.find(t, field)[1]]
    for pad in (40, 4095, 4096, 9000):  # a long run of numbers before: the window of the program is carried on
        assert ("(212) 555-0199", "phone") in spans(" ".join(["5"] * pad) + " (212) 555-0199 now")
    assert ("212-555-0199", "phone") in spans("ring 212-555-0199 now")
    assert spans("a plain text of 12 words in 2024, v1.2") == []


def test_token_rollup_is_exact_and_idempotent(spark, tmp_path, small):
    import tiktoken

    roll = tokencounts.Rollup(spark, str(tmp_path / "roll"))
    rows = docs(spark, small).select("doc_id", "source", "lang", "text")
    counted = tokencounts.counted(rows, "/opt/tokenizers/byte_bpe_50k.tiktoken").withColumn("op", F.lit("insert")).withColumn("old_tokens", F.lit(None).cast("long")).cache()
    with open("/opt/tokenizers/byte_bpe_50k.tiktoken", "rb") as f:
        enc = tokencounts._encoding(f.read())
    assert isinstance(enc, tiktoken.Encoding)
    want = Counter()
    for r in rows.collect():
        want[r["source"], r["lang"]] += len(enc.encode_ordinary(r["text"]))
    assert roll.apply("1", tokencounts.deltas(counted, "v1")) and not roll.apply("1", tokencounts.deltas(counted, "v1"))
    assert {(r["source"], r["lang"]): r["tokens"] for r in roll.totals().collect()} == dict(want)
    revised = counted.filter("doc_id < 10").withColumn("op", F.lit("revise")).withColumn("old_tokens", F.col("tokens")).withColumn("tokens", F.col("tokens") + 5)
    roll.apply("2", tokencounts.deltas(revised, "v1"))
    assert roll.totals().agg(F.sum("tokens"), F.sum("docs")).first()[:] == (sum(want.values()) + 50, rows.count())
    roll.apply("3", tokencounts.deltas(counted.withColumn("op", F.lit("delete")), "v1"))
    roll.apply("4", tokencounts.deltas(revised.withColumn("tokens", F.col("old_tokens")).withColumn("old_tokens", F.col("old_tokens") + 5), "v1"))
    assert roll.totals().count() == 0 and roll.batches() == ["1", "2", "3", "4"]
    (tmp_path / "roll" / "batch=5").mkdir()
    assert roll.batches() == ["1", "2", "3", "4"]  # without its marker a batch does not count


def test_token_rollup_merges_and_remembers(spark, tmp_path):
    kind = "source string, lang string, op string, tokens long, old_tokens long, size int"
    changes = lambda *rows: tokencounts.deltas(spark.createDataFrame([(*r, 1) for r in rows], kind), "v")
    roll, want = tokencounts.Rollup(spark, str(tmp_path / "r"), every=2), 0
    for k in range(5):
        assert roll.apply(f"b{k}", changes(("s", None, "insert", 10 + k, None)))
        want += 10 + k
        assert len(roll.pending()) < 2 and [tuple(r) for r in roll.totals().collect()] == [("s", None, "v", k + 1, want)]
        assert not roll.apply("b0", changes(("s", None, "insert", 99, None)))  # merged or not
    assert roll.version() == 2 and len([p for p in (tmp_path / "r").iterdir()]) == 2 and roll.batches() == [f"b{k}" for k in range(5)]
    roll.apply("odd", changes(("s", None, "revise", 4, None), ("s", None, None, 7, None), ("s", None, "other", 7, None), ("s", None, "insert", None, None), (None, "en", "delete", 3, None)))
    got = {tuple(r)[:3]: tuple(r)[3:] for r in roll.totals().collect()}
    assert got == {("s", None, "v"): (6, want + 4), (None, "en", "v"): (-1, -3)}
    (tmp_path / "r" / f"totals={roll.version() + 1}").mkdir()  # a merge that was lost leaves the old version in force
    assert {tuple(r)[:3]: tuple(r)[3:] for r in roll.totals().collect()} == got
    assert roll.apply("none", changes().limit(0)) and {tuple(r)[:3] for r in roll.totals().collect()} == set(got)


def test_token_count_query(spark, small):
    got = {(r["source"], r["lang"], r["tokenizer"]): (r["docs"], r["tokens"]) for r in queries.op2_token_counts(spark, small).collect()}
    want = Counter(), Counter()
    for r in docs(spark, small).collect():
        want[0][r["source"], r["lang"]] += 1
        want[1][r["source"], r["lang"]] += len(re.findall(r"[^\x20\x09-\x0D]+", r["text"] or ""))
    assert {k[:2]: v for k, v in got.items() if k[2] == "words"} == {k: (want[0][k], want[1][k]) for k in want[0]}
    assert {k[:2]: v[0] for k, v in got.items() if k[2] == "byte_bpe_50k"} == dict(want[0])


def test_quality_agrees_with_labels(spark, mid):
    got = queries.op3_quality(spark, mid).join(table(spark, mid, "labels"), "doc_id").collect()
    good = [r["kept"] for r in got if r["quality"] == 1]
    bad = [r["kept"] for r in got if r["quality"] == 0]
    assert np.mean(good) > 0.93 and np.mean(bad) < 0.25


def test_em_recovers_accuracies():
    rng = np.random.default_rng(0)
    y = rng.random(20_000) < 0.7
    accuracy = np.array([0.9, 0.8, 0.75, 0.7, 0.65, 0.85, 0.6, 0.95])
    votes = np.where(rng.random((len(y), 8)) < accuracy, np.where(y, 1, -1)[:, None], np.where(y, -1, 1)[:, None])
    pattern, where, n = np.unique(votes, axis=0, return_inverse=True, return_counts=True)
    post, tab, prior = quality.estimate(pattern, n.astype(float))
    assert abs(prior - 0.7) < 0.05 and np.abs(tab[:, 0, 2] - accuracy).max() < 0.06
    assert ((post[where.ravel()] > 0.5) == y).mean() > 0.95


def brute_classes(rows, least=0.8):
    """Class per id by all pairs of texts that share a shingle."""
    n = len(rows)
    df, vec = Counter(), []
    for _, t in rows:
        _, h, tf = minhash.shingled(*minhash.encoded([t]))
        vec.append((h, tf))
        df.update(h.tolist())
    bound = max(2, int(np.ceil(minhash.SHARE * n)))
    heavy = [k for k, c in df.items() if c >= bound]
    known = minhash.Weights(np.array(heavy, np.uint64), np.array([float(df[k]) for k in heavy]), n, bound)
    vec = [(h, tf * known.of(h)) for h, tf in vec]
    parent = list(range(n))

    def root(v):
        while parent[v] != v:
            v = parent[v]
        return v

    for i in range(n):
        for j in range(i):
            if rows[i][1] == rows[j][1] or minhash.weighted_jaccard(vec[i], vec[j]) >= least - 1e-9:
                a, b = root(i), root(j)
                parent[max(a, b)] = min(a, b)
    ids = [i for i, _ in rows]
    return {ids[i]: min(ids[k] for k in range(n) if root(k) == root(i)) for i in range(n)}


def test_minhash_equals_brute_force(spark, small):
    rows = sorted((r["doc_id"], r["text"]) for r in docs(spark, small).collect())
    base = "the quick brown fox jumps over the lazy dog and runs through the green field to find a quiet place by the river bank".split()
    for k in range(40):  # a crowd of near copies that are not all close to one leader
        w = list(base * 4)
        for j in range(k % 7):
            w[(k * 13 + j * 29) % len(w)] = f"edit{k}{j}"
        rows.append((10_000 + k, " ".join(w)))
    got = {r["doc_id"]: r["class_id"] for r in minhash.classes(frame(spark, rows)).collect()}
    assert got == brute_classes(rows)


def test_consistent_sampling_estimates_weighted_jaccard():
    rng = np.random.default_rng(1)
    h = np.sort(rng.integers(0, 1 << 48, 900).astype(np.uint64))
    w1, w2 = np.where(rng.random(900) < 0.8, 4.0, rng.random(900) * 8 + 0.1), np.where(rng.random(900) < 0.8, 4.0, rng.random(900) * 8 + 0.1)
    want = np.minimum(w1, w2).sum() / np.maximum(w1, w2).sum()
    hits = [(minhash.signatures(h, w1, np.array([0]), 4.0, s) == minhash.signatures(h, w2, np.array([0]), 4.0, s)).mean() for s in range(8)]
    assert abs(np.mean(hits) - want) < 0.08


def test_language_held_out(spark, mid):
    got = queries.op5_language_id(spark, mid)
    d = docs(spark, mid).select("doc_id", "lang")
    r = got.join(d, "doc_id").collect()
    held = [x for x in r if x["held_out"]]
    assert all(x["held_out"] == (zlib.crc32(str(x["doc_id"]).encode()) % 5 == 0) for x in r)
    assert np.mean([x["lang_pred"] == x["lang"] for x in held]) > 0.98 and all(0 <= x["score"] <= 1 for x in r)


def test_kneser_ney_sums_to_one():
    counts = {"a": Counter(), "b": Counter()}
    for lang, text in (("a", "abab abba abc bca cab "), ("b", "xyxy yxz abz zab ")):
        codes = "".join(map(chr, langid.letters(text * 3)))
        counts[lang].update(codes[i : i + langid.ORDER] for i in range(len(codes) - langid.ORDER + 1))
    model = langid.build({k: dict(v) for k, v in counts.items()})
    letters = sorted({g[-1] for c in counts.values() for g in c})
    for context in ("   ", "aba", " xy", "zzz"):
        texts = [context + c for c in [*letters, "q"]]
        p = np.exp([model.score(np.array([ord(c) for c in t], np.uint32))[0] for t in texts])
        assert np.allclose(p.sum(axis=0), 1, atol=2e-3)


def test_language_models_from_spark_equal_those_of_counts(spark, mid):
    rows = docs(spark, mid).filter("lang is not null").select("doc_id", "lang", "text").limit(60)
    counts = {}
    for r in rows.collect():
        codes = "".join(map(chr, langid.letters(r["text"])))
        counts.setdefault(r["lang"], Counter()).update(codes[i : i + langid.ORDER] for i in range(len(codes) - langid.ORDER + 1))
    want, got = langid.build(counts), langid.train(spark.createDataFrame(rows.collect(), rows.schema))
    assert want.langs == got.langs and all((a == b).all() for a, b in zip(want.keys, got.keys)) and all(np.allclose(a, b, atol=1e-5) for a, b in zip([*want.logp, *want.gamma], [*got.logp, *got.gamma]))


def test_language_models_keep_every_gram(spark):
    rng = np.random.default_rng(4)
    texts = ["".join(map(chr, 0x4E00 + rng.integers(0, 60, 400))) for _ in range(800)]
    model = langid.train(spark.createDataFrame([(i, "zz", t) for i, t in enumerate(texts)], "doc_id long, lang string, text string"), calibration=5)
    want = {s[i : i + 4] for t in texts for s in [f"   {t} "] for i in range(len(s) - 3)}
    assert len(want) > 300_000 and len(model.keys[langid.ORDER - 1]) == len(want)


def test_toxicity_held_out(spark):
    d = "/root/testdata/sf0.1"
    got = queries.op6_toxicity(spark, d).join(table(spark, d, "labels"), "doc_id").collect()
    held = [r for r in got if r["held_out"]]
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in got)
    assert np.mean([r["predicted"] for r in held if r["toxic"] == 1]) > 0.75 and np.mean([r["predicted"] for r in held if r["toxic"] == 0]) < 0.06


def test_toxicity_prior_of_all_labels(spark, monkeypatch):
    """The sample's class ratio is set by its bounds; the calibrated intercept follows that of all training labels."""
    d = frame(spark, [(i, f"text {i} of some words") for i in range(1200)])
    labels = spark.createDataFrame([(i, int(i % 6 == 0)) for i in range(1200)], "doc_id long, toxic int")
    monkeypatch.setattr(toxicity, "POSITIVES", 50)
    monkeypatch.setattr(toxicity, "NEGATIVES", 40)
    seen = []
    monkeypatch.setattr(toxicity, "fit", lambda texts, y: seen.append(y.mean()) or toxicity.Network(np.zeros(1), {}, 1.0, 0.25))
    net = toxicity.train(d, labels)
    y = [int(i % 6 == 0) for i in range(1200) if zlib.crc32(str(i).encode()) % 4 != 2]
    assert seen == [50 / 90]
    assert net.shift == pytest.approx(0.25 + np.log(sum(y) / (len(y) - sum(y))) - np.log(50 / 40))


def test_toxicity_reads_long_words_to_their_end():
    head = "".join(chr(97 + i * i % 23) for i in range(1500))
    net = toxicity.fit(["good calm words here"] * 20 + ["vile zzkkqq words here"] * 20, np.array([0] * 20 + [1] * 20))
    batch = pa.RecordBatch.from_pydict({"doc_id": [1, 2, 3], "text": [head, head + "zzkkqq", "_".join([*["calm"] * 200, "zzkkqq"])]})
    got = next(toxicity.scorer(SimpleNamespace(value=net))([batch])).to_pydict()
    assert got["score"][1] > got["score"][0] + 1e-3
    for text in (head, "_".join([head[:100]] * 9), "é" * 199 + "." * 300, "x" * 201, "plain words " + head):
        plain = [toxicity._plain(w) for w in text.split()]
        grams = {w[i : i + 5] for w in plain for i in range(len(w) - 4)}
        pieces = toxicity.words_of(text)
        assert grams == {p[i : i + 5] for p in map(toxicity._plain, pieces) for i in range(len(p) - 4)} and all(len(toxicity._plain(p)) <= toxicity.LONGEST for p in pieces)


def test_recurrent_gradients():
    rng = np.random.default_rng(0)
    w = {"o": rng.normal(size=16), "a": rng.normal(size=16), "k": np.zeros(1)}
    for d in "fb":
        w |= {"w" + d: rng.normal(size=(toxicity.INPUTS, 24)) * 0.3, "u" + d: rng.normal(size=(8, 24)) * 0.3, "c" + d: np.zeros(24)}
    net = toxicity.Network(np.zeros(1), w)
    rows = np.vstack((np.zeros((1, toxicity.INPUTS)), rng.normal(size=(9, toxicity.INPUTS))))
    idx = np.array([[1, 2, 3, 4, 0, 0], [5, 6, 7, 8, 9, 1]])
    g = np.array([0.7, -1.1])
    loss = lambda: float(toxicity.forward(net, rows, idx)[0] @ g)
    _, tape = toxicity.forward(net, rows, idx, keep=True)
    grad = toxicity.backward(net, rows, tape, g)
    for k in w:
        i = np.unravel_index(int(np.abs(grad[k]).argmax()), grad[k].shape)
        old = w[k][i]
        w[k][i] = old + 1e-3
        up = loss()
        w[k][i] = old - 1e-3
        down = loss()
        w[k][i] = old
        assert grad[k][i] == pytest.approx((up - down) / 2e-3, rel=0.05, abs=1e-3)
    for i in ((3, 5), (9, 1), (1, 0)):  # what the inputs learn
        old = rows[i]
        rows[i] = old + 1e-3
        up = loss()
        rows[i] = old - 1e-3
        down = loss()
        rows[i] = old
        assert grad["rows"][i] == pytest.approx((up - down) / 2e-3, rel=0.05, abs=1e-3)


def test_toxicity_learns_nothing_from_noise():
    """With labels drawn at random, calibrated scores of the training texts stay near the classes' share: no input holds its label."""
    rng = np.random.default_rng(8)
    texts = [" ".join(f"w{k}" for k in rng.integers(0, 4000, 30)) for _ in range(240)]
    labels = (rng.random(240) < 0.4).astype(int)
    net = toxicity.fit(texts, labels, least_epochs=4, least_steps=60)
    best, _ = toxicity.strongest(net, toxicity.Vocabulary(net), [t.split() for t in texts])
    p = toxicity._sigmoid(net.slope * best + net.shift)
    fresh = [" ".join(f"w{k}" for k in rng.integers(0, 4000, 30)).split() for _ in range(200)]
    q = toxicity._sigmoid(net.slope * toxicity.strongest(net, toxicity.Vocabulary(net), fresh)[0] + net.shift)
    assert abs(np.mean(q) - 0.4) < 0.15 and np.mean(p) < 0.7


def test_windows_cover_and_overlap():
    for n in (0, 1, 31, 32, 33, 52, 53, 1000):
        at, text = toxicity.windows(np.array([n]))
        seen = set(at[at >= 0].tolist())
        assert seen == set(range(n)) and len(at) == len(text)
        assert all(set(a[a >= 0]) & set(b[b >= 0]) for a, b in zip(at, at[1:]))


def test_mixing_meets_targets_and_repeats(spark, mid):
    a = sorted(map(tuple, queries.op7_mixing_to_targets(spark, mid).collect()), key=str)
    b = sorted(map(tuple, mixing.taken_by_document(*mixing.mix_sources(mixing.sized(docs(spark, mid).repartition(7)))).collect()), key=str)
    assert a == b
    per = {}
    for _, size, total, target, taken, shards, source in a:
        assert taken <= 3 * size and 128 * (len(shards) - 1) < max(1, taken + 128 * 3) and bool(shards) == bool(taken)
        t = per.setdefault(source, [0, 0, target, total])
        t[0] += taken
        t[1] += size
    assert all(abs(t[0] - t[2]) <= 128 and t[1] == t[3] for t in per.values())
    assert sum(t[2] for t in per.values()) == pytest.approx(sum(t[1] for t in per.values()))


def test_mixing_equals_brute_force(spark):
    """Ranks, taken words and shards of the layout from the definition; repeated ids, equal rows, a null id and source."""
    rng = np.random.default_rng(3)
    rows = [(int(i) if i % 9 else None, " ".join(f"w{i}{k}" for k in range(int(rng.integers(0, 60)))), "en", [None, "a", "b", "c"][i % 4 if i % 3 else 1]) for i in range(160)]
    rows += [(7, "the same row many times over", "en", "b")] * 1500 + [(7, "same id, other text", "en", "b"), (7, "same id, other words", "en", "b"), (8, None, "en", "a")]
    results = []
    for order in (rows, rows[::-1]):
        layout, held, by_source = mixing.mix_sources(mixing.sized(frame(spark, order).repartition(3)), block_words=8, blocks_per_shard=100, blocks_per_bucket=16)
        got, per_source = layout.collect(), {r["code"]: r for r in by_source.collect()}
        results.append(sorted(map(str, mixing.taken_by_document(layout, held, by_source).collect())))
        own = sorted({(tuple(r[c] for c in mixing.DOCUMENT)) for r in held.collect()}, key=str)
        assert len(own) == len(rows)
        blocks = spark.createDataFrame([(*d, b, min(8, d[2] - 8 * b)) for d in own for b in range(-(-d[2] // 8))], "doc_id long, code int, size long, digest long, twin long, block int, words long")
        drawn = [(r["code"], r["draw"] % (1 << 64), (*(r[c] for c in mixing.DOCUMENT), r["block"]), r["words"]) for r in blocks.withColumn("draw", F.xxhash64(F.lit(7), *mixing.DOCUMENT, "block")).collect()]
        quotas, sequence = [], []
        for c in sorted(per_source):
            mine = [(k, w) for code, _, k, w in sorted(drawn, key=lambda r: r[1]) if code == c]
            words, target = sum(w for _, w in mine), per_source[c]["target"]
            assert words == per_source[c]["source_size"]
            whole, upto, front = (int(target // words) if words else 0), 0, 0
            for _, w in mine:
                upto += w
                front += upto - w / 2 <= target - whole * words
            quotas.append(min(3 * len(mine), whole * len(mine) + (front if target > whole * words else 0)))
            sequence.append([(*mine[p % len(mine)][0], p // len(mine)) for p in range(quotas[-1])])
        tree = mixing.SplittingTree(quotas, max(1, -(-sum(quotas) // 100)), 7)
        want = {key: k for s, q in enumerate(quotas) for k, a, b in tree.runs(s, 0, q) for key in sequence[s][a:b]}
        assert {(*(r[c] for c in mixing.DOCUMENT), r["block"], r["epoch"]): r["shard"] for r in got} == want and len(got) == sum(quotas)
        mix = mixing.shuffled_mix(frame(spark, order), layout, by_source, 8).collect()
        assert len(mix) == len(got) and Counter(len(r["text"].split()) for r in mix) == Counter(r["words"] for r in got)
    assert results[0] == results[1]


def test_targets_water_fill():
    assert mixing.targets({"a": 100, "b": 1, "c": 100, None: 0}) == pytest.approx({"a": 49.5, "b": 3, "c": 148.5, None: 0})
    assert mixing.targets({}) == {} and mixing.targets({"z": 5}) == {"z": 5}


def test_splitting_tree_is_exact_and_local(spark, small, monkeypatch):
    layout, held, by_source = mixing.mix_sources(mixing.sized(docs(spark, small)), block_words=32, blocks_per_shard=64, blocks_per_bucket=128)
    rows = layout.collect()
    per = Counter(r["shard"] for r in rows)
    assert max(per.values()) - min(per.values()) <= 2 and len(per) == -(-len(rows) // 64)
    assert len({(r["doc_id"], r["digest"], r["twin"], r["block"], r["epoch"]) for r in rows}) == len(rows)
    tree = mixing.SplittingTree([50, 30, 7], 9, 1)
    got = {s: [(k, b - a) for k, a, b in tree.runs(s, 0, q)] for s, q in enumerate((50, 30, 7))}
    assert [sum(n for _, n in got[s]) for s in got] == [50, 30, 7]
    monkeypatch.setattr(mixing, "KEPT", 2)  # a tree that forgets deals every position alike
    again = mixing.SplittingTree([50, 30, 7], 9, 1)
    assert got == {s: [(k, b - a) for k, a, b in again.runs(s, 0, q)] for s, q in enumerate((50, 30, 7))}
    assert [k for k, _, _ in again.runs(1, 10, 20)][0] == next(k for k, a, b in tree.runs(1, 10, 20))
    mix = mixing.shuffled_mix(docs(spark, small), layout, by_source, 32)
    assert mix.count() == len(rows)


def brute_lines(rows, least=8):
    """Kept lines by the definition of templates, over all pairs of lines of different documents."""
    seen, cut = {}, {}
    for i, t in rows:
        for k, line in enumerate((t or "").split("\n")):
            w = [x for x in re.sub(r"[^\x20\x09-\x0D]*[0-9][^\x20\x09-\x0D]*", "<*>", line).split(" ") if x]
            if len(w) < least:
                continue
            n = len(w) - 3
            edge = [3 + n * r // 4 for r in range(5)]
            piece = [tuple(w[a:b]) for a, b in zip(edge, edge[1:])]
            keys = [(len(w), tuple(w[:3]), 4, *piece)] + [(len(w), tuple(w[:3]), r, *(p for j, p in enumerate(piece) if j != r)) for r in range(4)]
            for key in keys:
                seen.setdefault(key, set()).add(i)
                cut.setdefault((i, k), []).append(key)
    gone = {at for at, keys in cut.items() if any(min(seen[k]) < at[0] for k in keys)}
    return {i: "\n".join(x for k, x in enumerate(t.split("\n")) if (i, k) not in gone) for i, t in rows}


def test_line_dedup_equals_brute_force(spark, mid):
    rows = [(r["doc_id"], r["text"]) for r in docs(spark, mid).collect()]
    rows += [(5000 + i, f"Order {i} was shipped on day {i * 7} to the customer in town\nshort line {i}") for i in range(5)]
    got = {r["doc_id"]: r["text"] for r in linededup.dedup_lines(frame(spark, rows)).collect()}
    assert got == brute_lines(rows)
    assert got[5003] == "short line 3" and got[5000].startswith("Order 0")


def brute_every_line(rows):
    """As ``brute_lines``, for lines down to one token."""
    seen, cut = {}, {}
    for i, t in rows:
        for k, line in enumerate((t or "").split("\n")):
            masked = re.sub(r"[^\x20\x09-\x0D]*[0-9][^\x20\x09-\x0D]*", "<*>", line)
            own, w, rest = [x for x in line.split(" ") if x], [x for x in masked.split(" ") if x], masked.replace("<*>", "")
            if not line.strip(" \t\n\v\f\r"):
                continue
            if len(w) < 8 and re.search("[0-9]", line) and (not any(c.isalpha() for c in rest) or len(line.encode()) - len(rest.encode()) > 64):
                w = own
            keys = [(len(w), tuple(w))]
            if len(w) >= 7:
                edge = [3 + (len(w) - 3) * r // 4 for r in range(5)]
                keys += [(len(w), r, tuple(w[:a]), tuple(w[b:])) for r, (a, b) in enumerate(zip(edge, edge[1:]))]
            for key in keys:
                seen.setdefault(key, set()).add(i)
                cut.setdefault((i, k), []).append(key)
    gone = {at for at, keys in cut.items() if any(min(seen[k]) < at[0] for k in keys)}
    return {i: "\n".join(x for k, x in enumerate(t.split("\n")) if (i, k) not in gone) for i, t in rows}


def test_line_dedup_takes_every_line(spark, mid, tmp_path):
    rows = [(r["doc_id"], r["text"]) for r in docs(spark, mid).collect()]
    rows += [(6000 + i, f"All rights reserved.\nown{chr(97 + i)} words\n\n\r\n{i}{i}\n7\n| {i} | {i * 3} |\nChapter {i}\nYou can find it{chr(97 + i)}.\nsee 年{i}{'月' * 30}{i}\nOnly") for i in range(4)]
    frame(spark, rows).write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["doc_id"]: r["text"] for r in queries.op8_line_dedup(spark, str(tmp_path)).collect()}
    assert got == brute_every_line(rows)
    assert got[6002] == f"ownc words\n\n\r\n22\n| 2 | 6 |\nYou can find itc.\nsee 年2{'月' * 30}2"
    staged = corpus_pipeline.drop_repeated_lines(spark, table(spark, str(tmp_path), "documents"), str(tmp_path))
    assert {r["doc_id"]: r["text"] for r in staged.collect()} == got


def brute_leaks(rows, items, least=0.8):
    """Pairs of document and item with a window of the item's size of that similarity, over all windows."""
    words = lambda t: [w for w in re.split(r"[\W_]+", (t or "").lower()) if w]
    grams = lambda w, k: Counter(tuple(w[i : i + k]) for i in range(len(w) - k + 1))
    bench = [(i, w, min(5, len(w)), grams(w, min(5, len(w)))) for i, t in items if (w := words(t))]
    df = Counter(g for _, _, _, c in bench for g in c)
    n = len(bench)
    weight = lambda g: 1 + np.log(n / df[g]) if g in df else 1 + np.log(n)
    out = set()
    for i, t in rows:
        w = words(t)
        own = {k: set(grams(w, k)) for k in {k for _, _, k, _ in bench}}
        for j, b, k, c in bench:
            if own[k].isdisjoint(c):
                continue
            for a in range(max(1, len(w) - len(b) + 1)):
                d = grams(w[a : a + len(b)], k)
                both = sum(min(d[g], c[g]) * weight(g) for g in d if g in c)
                if both / (sum(v * weight(g) for g, v in d.items()) + sum(v * weight(g) for g, v in c.items()) - both) >= least - 1e-9:
                    out.add((i, j))
    return out


def test_decontamination_equals_brute_force(spark, small):
    rows = [(r["doc_id"], r["text"]) for r in docs(spark, small).collect()]
    items = [(r["item_id"], r["text"]) for r in table(spark, small, "benchmark").collect()]
    for k, (_, t) in enumerate(items[:12]):  # leaks with one word changed, dropped or added
        w = t.split()
        w[len(w) // 2 : len(w) // 2 + (k % 3 == 1)] = ["altered"] * (k % 3 != 1)
        rows.append((9000 + k, "some words before it " + " ".join(w) + " and some behind"))
    want = brute_leaks(rows, items)
    got = {(r["doc_id"], r["item_id"]) for r in decontam.matches(frame(spark, rows), spark.createDataFrame(items, "item_id long, text string")).collect()}
    assert got == want and sum(i >= 9000 for i, _ in got) >= 2
    left = {r["doc_id"] for r in decontam.decontaminate(frame(spark, rows), spark.createDataFrame(items, "item_id long, text string")).collect()}
    assert left == {i for i, _ in rows} - {i for i, _ in want}


def test_blocks_guarantee_the_radius_and_are_selective(spark):
    rng = np.random.default_rng(0)
    a, other = rng.integers(-(1 << 63), (1 << 63) - 1, (2, 600))
    flips = [sum(1 << int(b) for b in rng.choice(63, decontam.RADIUS, replace=False)) for _ in a]
    left = spark.createDataFrame([(i, int(x)) for i, x in enumerate(a)], "i long, print long").withColumn("on", F.lit(0)).cache()
    near = spark.createDataFrame([(i, int(x) ^ f) for i, (x, f) in enumerate(zip(a, flips))], "j long, print2 long").withColumn("on", F.lit(0))
    assert decontam.near_prints(left, near, ["on"]).filter("i = j").select("i").distinct().count() == 600
    far = spark.createDataFrame([(i, int(x)) for i, x in enumerate(other)], "j long, print2 long").withColumn("on", F.lit(0))
    asked, block = left.select("i", F.explode(decontam.blocks(F.col("print"))).alias("_b")), F.explode(decontam.blocks(F.col("print2"))).alias("_b")
    around = F.explode(F.array(*map(F.lit, decontam.flips()))).alias("x")
    stored = far.select("j", block).select("j", "_b", around).select("j", F.struct(F.col("_b.block").alias("block"), F.col("_b.value").bitwiseXOR(F.col("x")).alias("value")).alias("_b"))
    assert asked.join(stored, "_b").count() < 0.01 * 600 * 600  # unrelated pairs that meet


def test_decontamination_recall_of_edited_items(spark):
    """Passages with words changed, dropped or added against all windows: what the fingerprint loses of similarity 0.8 or more."""
    rng = np.random.default_rng(5)
    vocabulary = np.array([f"w{i}" for i in range(3000)])
    items, rows = [], []
    for i in range(150):
        w = list(rng.choice(vocabulary, rng.integers(30, 90)))
        items.append((i, " ".join(w)))
        for k in range(2):
            v = list(w)
            for _ in range(k + 1):
                at = int(rng.integers(0, len(v)))
                v[at : at + int(rng.integers(0, 2))] = list(rng.choice(vocabulary, rng.integers(0, 2)))
            rows.append((2 * i + k, " ".join([*rng.choice(vocabulary, 20), *v, *rng.choice(vocabulary, 20)])))
    want = brute_leaks(rows, items)
    got = {(r["doc_id"], r["item_id"]) for r in decontam.matches(frame(spark, rows), spark.createDataFrame(items, "item_id long, text string")).collect()}
    assert got <= want and len(want) > 100 and len(got) >= 0.99 * len(want)


def test_decontamination_searches_every_text_of_an_id(spark):
    item = " ".join(f"quiz{i}" for i in range(30))
    rows = [(1, "a plain text"), (1, f"before {item} behind"), (2, "another text")]
    for order in (rows, rows[::-1]):
        got = decontam.matches(frame(spark, order), spark.createDataFrame([(1, item)], "item_id long, text string")).collect()
        assert [(r["doc_id"], r["position"], r["similarity"]) for r in got] == [(1, 1, 1.0)]


def test_embeddings_equal_brute_force(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(700, 16))
    x[600:] = x[:100] + rng.normal(size=(100, 16)) * rng.random((100, 1)) * 0.5
    x[650:660] = x[0]
    x = x.astype(np.float32)
    rows = [(int(i) * 3, [float(v) for v in e]) for i, e in enumerate(x)]
    got = {r["vec_id"]: r for r in embeddup.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<float>")).collect()}
    u = embeddup.units(x)
    near = u @ u.T >= 0.9
    n = near.sum(axis=1) - 1
    found = np.array([got[i * 3]["n_links"] for i in range(700)])
    assert (found <= n).all() and found.sum() >= 0.97 * n.sum()


def test_embedding_index_prunes_and_finds(spark, tmp_path):
    """20,000 vectors, 3000 planted partners at cosine 0.90 to 0.92, a crowd of near copies: recall while few cells are visited."""
    import pyarrow.parquet as pq

    rng = np.random.default_rng(1)
    n = 20_000
    x = rng.normal(size=(n, 64))
    x /= np.linalg.norm(x, axis=1)[:, None]
    z = rng.normal(size=(3000, 64))
    z -= (z * x[:3000]).sum(axis=1)[:, None] * x[:3000]
    c = rng.uniform(0.9, 0.92, (3000, 1))
    x[10_000:13_000] = c * x[:3000] + np.sqrt(1 - c * c) * z / np.linalg.norm(z, axis=1)[:, None]
    x[15_000:16_500] = x[9999] + rng.normal(size=(1500, 64)) * 0.028
    x = x.astype(np.float32)
    index = embeddup.MultiIndex(embeddup.units(x[::4]), n)
    assert index.visits <= 0.1 * len(index.c1) * len(index.c2)
    pq.write_table(pa.table({"vec_id": pa.array(range(n), pa.int64()), "embedding": pa.array(list(x), pa.list_(pa.float32()))}), f"{tmp_path}/e.parquet")
    got = embeddup.near_duplicates(spark.read.parquet(f"{tmp_path}/e.parquet")).toPandas().sort_values("vec_id")
    u = embeddup.units(x)
    want = np.concatenate([(u[lo : lo + 1000] @ u.T >= 0.9).sum(axis=1) - 1 for lo in range(0, n, 1000)])
    found = got["n_links"].to_numpy()
    assert (found <= want).all() and found.sum() >= 0.999 * want.sum() and (found == want).mean() > 0.99
    assert (found[10_000:13_000] >= 1).mean() >= 0.99 and got["component_id"].to_numpy()[15_000:16_500].max() == 9999


def test_embedding_codes_lose_few():
    rng = np.random.default_rng(2)
    x = embeddup.units(rng.normal(size=(20_000, 48)))
    index = embeddup.MultiIndex(x[:2000], 2000)
    z = rng.normal(size=x.shape)
    z -= (z * x).sum(axis=1)[:, None] * x
    y = 0.9 * x + np.sqrt(1 - 0.81) * z / np.linalg.norm(z, axis=1)[:, None]
    far = lambda a, b: np.unpackbits(index.codes(a) ^ index.codes(b), axis=1).sum(axis=1)
    assert (far(x, y) > index.apart).mean() < 1e-3 and (far(x, x[::-1]) <= index.apart).mean() < 1e-3


def test_embeddings_of_several_lengths_and_large_doubles(spark):
    rows = [(1, [1e300, 1e300, 0.0]), (2, [1e-300, 1e-300, 0.0]), (3, [1.0, 0.0, 0.0]), (4, [1.0, 1.0 + 1e-9]), (5, [1.0, 1.0]), (6, [1.0, -1.0]), (7, [3.0]), (8, [5.0]), (9, [-1.0])]
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in embeddup.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()}
    assert got == {1: (1, 1), 2: (1, 1), 3: (0, 3), 4: (1, 4), 5: (1, 4), 6: (0, 6), 7: (1, 7), 8: (1, 7), 9: (0, 9)}


def test_multi_sequence_order_is_sorted():
    rng = np.random.default_rng(0)
    d1, d2 = rng.random(9), rng.random(7)
    want = sorted(range(63), key=lambda c: d1[c // 7] + d2[c % 7])
    assert embeddup.multi_sequence(d1, d2, 63) == want and embeddup.multi_sequence(d1, d2, 5) == want[:5]


def test_block_similarities_equal_pairwise():
    rng = np.random.default_rng(6)
    texts = [" ".join(rng.choice(["aa", "bb", "cc", "dd"], rng.integers(1, 60))) for _ in range(14)] + ["aa " * 50]
    known = minhash.Weights(np.zeros(0, np.uint64), np.zeros(0), 15, 2)
    vec = []
    for t in texts:
        _, h, tf = minhash.shingled(*minhash.encoded([t]))
        vec.append((h, tf * known.of(h)))
    got = minhash.similarities(texts, known, np.arange(7), np.arange(7, 15))
    assert np.allclose(got, [[minhash.weighted_jaccard(vec[i], vec[j]) for j in range(7, 15)] for i in range(7)])


def test_crowded_bucket_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(minhash, "BLOCK_PAIRS", 3)
    monkeypatch.setattr(minhash, "BLOCK", 7)
    base = [f"w{i}" for i in range(60)]
    rows = []
    for k in range(45):
        w = list(base)
        for j in range(1 + k % 3):
            w[(k * 7 + j * 17) % 60] = f"e{k}{j}"
        rows.append((k, " ".join(w)))
    got = {r["doc_id"]: r["class_id"] for r in minhash.classes(frame(spark, rows)).collect()}
    assert got == brute_classes(rows)


def test_language_calibration_takes_every_row(spark):
    """Bounds and scale are the quantile and the median over all 3000 rows."""
    rows = [(i, "aa" if i % 2 else "bb", ("abab bab abba " if i % 2 else "cdcd dcd cddc ") * (1 + i % 5) + chr(97 + i % 4)) for i in range(3000)]
    model = langid.train(spark.createDataFrame(rows, "doc_id long, lang string, text string"))
    h, _ = langid.entropies(model, [t for _, _, t in rows])
    own = np.array([model.langs.index(g) for _, g, _ in rows])
    mine, other = h[np.arange(len(own)), own], h[np.arange(len(own)), 1 - own]
    assert all(abs(model.bound[k] - 1.25 * np.quantile(mine[own == k], 0.995)) < 1e-3 for k in (0, 1))
    assert abs(4 / model.scale - np.median(np.abs(other - mine))) < 1e-3


def test_few_edges_on_the_driver_equal_stars(spark):
    rng = np.random.default_rng(5)
    chain = [(3000 - i, 2999 - i) for i in range(40)]
    for edges in ([], [(7, 7)], chain, [(int(a), int(b)) for a, b in rng.integers(-60, 60, (70, 2))] + [(500, i) for i in range(600, 640)]):
        rows = spark.createDataFrame(edges, "a long, b long")
        assert sorted(components(rows, few=1 << 10).collect()) == sorted(components(rows).collect())


def near_rows(n):
    """Near copies in crowds of nine."""
    rows = []
    for k in range(n):
        w = [f"w{k // 9}x{i}" for i in range(60)]
        for j in range(1 + k % 3):
            w[(k * 7 + j * 17) % 60] = f"e{k}{j}"
        rows.append((k, " ".join(w)))
    return rows


def test_few_links_take_no_star_rounds(spark, monkeypatch):
    """Every table that a run writes costs a stage of all shuffle partitions, however few rows it has."""
    names, rows, write = [], near_rows(63), common.Scratch.__call__
    monkeypatch.setattr(common.Scratch, "__call__", lambda self, df, name: names.append(name) or write(self, df, name))
    got = sorted(minhash.classes(frame(spark, rows)).collect())
    assert "edges" not in names and len(names) <= 16
    assert {r["doc_id"]: r["class_id"] for r in got} == brute_classes(rows)
    monkeypatch.setattr(minhash, "FEW_LINKS", 0)  # as with many links
    monkeypatch.setattr(minhash, "BLOCK_PAIRS", 3)
    assert sorted(minhash.classes(frame(spark, rows)).collect()) == got and "edges" in names


def test_small_verification_leaves_memory_as_it_is(monkeypatch):
    trims, texts = [], [t for _, t in near_rows(30)] + ["", "one two"]
    monkeypatch.setattr(common, "trim", lambda: trims.append(1))
    monkeypatch.setattr(minhash, "CACHED", 150)
    monkeypatch.setattr(minhash, "PIECE", 1500)
    known = minhash.Weights(np.zeros(0, np.uint64), np.zeros(0), 32, 2)
    pairs = [(i, j) for i in range(32) for j in range(i)]
    a, b = zip(*pairs)
    columns = {"a": a, "b": b, "ca": [100 + i for i in a], "cb": [100 + j for j in b], "ta": [texts[i] for i in a], "tb": [texts[j] for j in b]}
    batch = pa.RecordBatch.from_pydict(columns)
    vec = [(h, tf * known.of(h)) for _, h, tf in (minhash.shingled(*minhash.encoded([t])) for t in texts)]
    want = [(100 + i, 100 + j) for i, j in pairs if minhash.weighted_jaccard(vec[i], vec[j]) >= 0.3]
    run = minhash._verifier(SimpleNamespace(value=known), 0.3)
    got = [tuple(r.values()) for out in run(iter([batch])) for r in out.to_pylist()]
    assert got == want and 0 < len(want) < len(pairs) and not trims
    monkeypatch.setattr(minhash, "TRIM", batch.nbytes)  # beyond the bound at the start and at the end
    assert sum(out.num_rows for out in minhash._verifier(SimpleNamespace(value=known), 0.3)(iter([batch, batch]))) == 2 * len(want) and len(trims) == 2
