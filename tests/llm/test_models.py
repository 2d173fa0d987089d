"""The learnt operators against plain loops: a text's features, chains, scores and spans one by one, and rates on one array."""

import math
import re

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from spangrid.llm import mixing, quality, toxicity
from spangrid.llm.flat import BYTE_CODE, mix, texts_of
from spangrid.llm.hashed import BITS, SCALE, Softmax

U = (1 << 64) - 1
BASE = 0x9E3779B97F4A7C15
LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
TEXTS = [None, "", " . ", "Idiot! you are an IDIOT", "one two three. four five\nsix", "é🙂 ñandú ok? yes-no", "a" * 300, "w1 " * 700, "The end.\n\nThe end.\n"]


def mixed(x):
    return int(mix(np.array([x & U], np.uint64))[0])


def fingerprint(raw):
    value = sum(int(BYTE_CODE[b]) * pow(BASE, j, 1 << 64) for j, b in enumerate(raw)) & U
    return mixed(value + len(raw) * 0xA0761D6478BD642F)


def chain_marginals(z, edge):
    """Shares of state 1 at each place of a chain, in sums over both states."""
    f = [(1.0, math.exp(z[0]))]
    for x in z[1:]:
        f.append(tuple(sum(f[-1][p] * math.exp(edge[p][q]) for p in (0, 1)) * (math.exp(x) if q else 1) for q in (0, 1)))
        s = sum(f[-1])
        f[-1] = (f[-1][0] / s, f[-1][1] / s)
    b = [(1.0, 1.0)]
    for x in reversed(z[1:]):
        b.append(tuple(sum(b[-1][q] * math.exp(edge[p][q]) * (math.exp(x) if q else 1) for q in (0, 1)) for p in (0, 1)))
        s = sum(b[-1])
        b[-1] = (b[-1][0] / s, b[-1][1] / s)
    return [u[1] * v[1] / (u[0] * v[0] + u[1] * v[1]) for u, v in zip(f, reversed(b))]


def tagged(field, text):
    """Score and spans of one text."""
    low = (text or "").translate(LOW)
    found = list(re.finditer(r"[0-9a-z\u0080-\U0010ffff]+", low))
    words = [m[0].encode() for m in found]
    chains, start = [], 0
    for i, m in enumerate(found):
        if i and (any(c in ".!?\n" for c in low[found[i - 1].start() : m.start()]) or i - start == toxicity.CHAIN):
            start = i
        chains.append(start)
    marks = [fingerprint(w) for w in words]
    z = []
    for i, w in enumerate(words):
        x = [marks[i], *(fingerprint(w[:k]) ^ (k * 0x51ED270B) for k in (4, 5, 6)), fingerprint(w[-4:]) ^ 0x7F4A7C15]
        x.append(marks[i - 1] ^ 0x1234567 if i and chains[i] == chains[i - 1] else 0)
        x.append(marks[i + 1] ^ 0x89ABCDE if i + 1 < len(words) and chains[i] == chains[i + 1] else 0)
        z.append(field.bias + sum(field.w[(v * BASE & U) >> (64 - toxicity.BITS)] for v in x))
    p = []
    for c in dict.fromkeys(chains):
        p += chain_marginals([v for v, own in zip(z, chains) if own == c], field.edge)
    x = [1, math.log1p(sum(p)), max(p, default=0), math.log1p(toxicity.SHARES * sum(p) / max(1, len(p)))]
    spans, i = [], 0
    while i < len(p):
        j = i
        while j < len(p) and p[j] >= 0.5:
            j += 1
        if j > i:
            spans.append(f"{found[i].start()}:{found[j - 1].end()}")
        i = max(j, i + 1)
    return 1 / (1 + math.exp(-sum(a * b for a, b in zip(x, field.doc)))), ",".join(spans)


def test_tags_against_loops(spark, labels, sf):
    field = toxicity.fit(spark.read.parquet(f"{sf}/documents.parquet"), labels)
    rng = np.random.default_rng(6)
    loud = toxicity.Field()
    loud.w, loud.edge, loud.doc = rng.normal(size=1 << toxicity.BITS), rng.normal(size=(2, 2)), rng.normal(size=4)
    some = [r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").orderBy(F.length("text")).limit(40).collect()]
    rows = list(enumerate(TEXTS + some))
    for model in (field, loud):
        got = {r["i"]: r for r in toxicity.tag(spark.createDataFrame(rows, "i int, text string"), model).collect()}
        for i, x in rows:
            score, spans = tagged(model, x)
            assert abs(got[i]["score"] - score) < 1e-6 and got[i]["spans"] == spans


def test_token_labels_against_loops():
    """A token of a toxic text is labelled if its word or prefix is in enough toxic texts, beside enough neighbours, and few others."""
    rng = np.random.default_rng(8)
    words = [f"word{i}" for i in range(30)]
    texts = [" ".join([*rng.choice(words, 6), "vile", *rng.choice(words, 6)]) for _ in range(20)] + [" ".join(rng.choice(words, 12)) for _ in range(20)]
    toxic = np.repeat([True, False], 20)
    parts = [toxicity.Tokens(t) for t in texts_of(pa.array(texts, pa.large_string()))]
    got = np.concatenate(toxicity._token_labels(parts, toxic))
    want = []
    for x, bad in zip(texts, toxic):
        want += [float(bad and w == "vile") for w in x.split()]
    assert got.tolist() == want


def logits(model, text):
    low = (text or "").translate(LOW)
    raw = low.encode()
    words = [fingerprint(w.encode()) for w in re.findall(r"[^\x20\x09-\x0D]+", low)]
    blocks = [words, [mixed(a * 3 + b) for a, b in zip(words, words[1:])]]
    for k in (3, 4):
        out = []
        for i in range(len(raw) - k + 1):
            g = 0
            for b in raw[i : i + k]:
                g = (g * 0x100000001B3 + int(BYTE_CODE[b])) & U
            out.append(mixed(g))
        blocks.append(out)
    z = np.array(model.b, float)
    for j, block in enumerate(blocks):
        if block:
            z = z + SCALE * np.mean([model.w[j][v >> (64 - BITS)] for v in block], axis=0, dtype=np.float64)
    return z


def test_quality_against_loops(spark, labels, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = quality.fit(docs.select("doc_id", "text"), labels)
    some = docs.orderBy(F.length("text")).limit(25).select("doc_id", "text")
    rows = [(r["doc_id"], r["text"]) for r in some.collect()] + [(-i, x) for i, x in enumerate(TEXTS, 1) if x is None or len(x) < 400]
    got = {r["doc_id"]: r for r in quality.judge(docs.select("doc_id", "text").unionByName(spark.createDataFrame([x for x in rows if x[0] < 0], "doc_id long, text string")), labels).collect()}
    for i, x in rows:
        z = logits(model, x) * model.heat
        p = 1 / (1 + math.exp(z[0] - z[1]))
        assert abs(got[i]["quality"] - p) < 1e-4
        assert got[i]["kept"] == (not got[i]["base_failed"] and got[i]["quality"] >= quality.KEEP)


@pytest.mark.parametrize("every", [2, 10])
def test_rates_against_one_array(spark, labels, sf, monkeypatch, every):
    """Rates by projected gradients over one array in memory; posteriors by the loops above."""
    monkeypatch.setattr(mixing, "STATE_EVERY", every)
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    docs = docs.unionByName(docs.limit(3)).unionByName(docs.limit(1).withColumns({"text": F.lit(None).cast("string"), "doc_id": F.lit(None).cast("long")}))
    targets = {"en": 0.55, "de": 0.25, "es": 0.05, "fr": 0.15}
    out, names = mixing.rates(docs, labels, targets)
    rows = out.toPandas()
    p, t = np.array(rows["p"].tolist()), rows["n_tokens"].to_numpy(float)
    goal = np.array([targets[c] for c in names])
    share = t @ p / t.sum()
    ridge = mixing.RIDGE * share.min()
    r = before = np.ones(len(t))
    for step in range(mixing.STEPS):
        y = r + step / (step + 3) * (r - before)
        gap = (y * t) @ p / t.sum() - goal
        if np.abs(gap).max() < mixing.CLOSE:
            break
        r, before = np.maximum(0, y - (p @ gap + ridge * (y - 1)) / (1 + ridge)), r
    assert np.allclose(rows["rate"], r, atol=1e-6) and np.abs((r * t) @ p / t.sum() - goal).max() < 10 * mixing.CLOSE
    model = mixing.learn(docs.select("doc_id", "text", F.col("lang").alias("domain")), labels, sorted(targets))
    assert isinstance(model, Softmax) and model.classes == names
    for x in docs.orderBy(F.length("text")).limit(10).collect():
        z = logits(model, x["text"]) * model.heat
        want = np.exp(z - z.max()) / np.exp(z - z.max()).sum()
        mine = rows[rows["doc_id"] == x["doc_id"]] if x["doc_id"] is not None else rows[rows["doc_id"].isna()]
        assert np.allclose(mine["p"].iloc[0], want, atol=1e-4)
