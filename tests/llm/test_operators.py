"""Each operator against a brute-force version on small fixtures, with null, empty, long and repeated rows."""

import collections
import hashlib
import math
import re
import zlib

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from spangrid.llm import bpe, minhash, mixing, quality, rangejoin, secrets, sharding, suffixes, suffixtree, toxicity
from spangrid.llm.components import components

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
FILE = public_tokenizers.path("byte_bpe_50k.json")


def key(x):
    return tuple((v is not None, v) if not isinstance(v, float) else (True, round(v, 5)) for v in x)


def same(got, want):
    assert sorted(map(key, got)) == sorted(map(key, want))


def sha(b):
    return hashlib.sha256(b).hexdigest()


def test_bpe(docs, local, nothing):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(FILE)
    want = []
    for i, x in local:
        ids = t.encode(x or "", add_special_tokens=False).ids
        want.append((i, len(ids), sha(np.array(ids, "<u4").tobytes()), sha(t.decode(ids, skip_special_tokens=False).encode())))
    same([tuple(r) for r in bpe.digests(docs, FILE).collect()], want)
    both = bpe.encode(docs, FILE, back="again")
    assert both.columns == ["doc_id", "text", "score", "ids", "again"]
    assert both.filter(F.col("again") != F.coalesce("text", F.lit(""))).isEmpty()
    odd = docs.sparkSession.createDataFrame([(1, [72, 105]), (2, None), (3, []), (4, [72])], "doc_id long, ids array<int>")
    assert {r["doc_id"]: r["decoded"] for r in bpe.decode(odd, FILE).collect()} == {i: t.decode(x or [], skip_special_tokens=False) for i, x in ((1, [72, 105]), (2, None), (3, []), (4, [72]))}
    back = bpe.decode(bpe.encode(docs, FILE), FILE)
    assert back.columns == ["doc_id", "text", "score", "ids", "decoded"]
    assert back.filter(F.col("decoded") != F.coalesce("text", F.lit(""))).isEmpty()
    assert bpe.digests(nothing, FILE).isEmpty()


@pytest.mark.parametrize("k", [4, 5])
def test_minhash(docs, local, nothing, k):
    sets = {}
    for i, x in local:
        w = WORD.findall((x or "").translate(LOW))
        sets[i] = frozenset(tuple(w[j : j + k]) for j in range(max(1, len(w) - k + 1))) if w else frozenset()
    root = {i: i for i in sets}
    ids = [i for i in sets if i is not None and sets[i]]
    for a in ids:
        for b in ids:
            c = len(sets[a] & sets[b]) if a < b else 0
            if c and 100 * c >= 80 * (len(sets[a]) + len(sets[b]) - c):
                ra, rb = root[a], root[b]
                for x in root:
                    if root[x] in (ra, rb):
                        root[x] = min(ra, rb)
    want = [(i, len(sets[i]), root[i] if i is not None else None, i is None or root[i] == i) for i, _ in local]
    same([tuple(r) for r in minhash.near_duplicates(docs, k).collect()], want)
    assert minhash.near_duplicates(nothing, k).isEmpty()
    assert minhash.keep_one(docs, k).columns == docs.columns


@pytest.mark.parametrize("shared", [minhash.WIDTH - 1, minhash.WIDTH, minhash.WIDTH + 1, 2 * minhash.WIDTH + 1])
def test_tied_counts_every_shared_shingle(shared):
    """Links exactly at the limit, at and around whole blocks of shared shingles."""
    import pyarrow as pa

    union = shared * 100 // 80
    sets = [np.arange(shared), np.arange(union)]
    table = lambda sets: pa.table({"rep": [1, 2], "c": pa.array([1, 2], pa.int64()), "shingles": pa.array([x.tolist() for x in sets], pa.list_(pa.int64()))})
    assert minhash._tied(80)(table(sets)).to_pylist() == [{"a": 1, "b": 2}]
    assert minhash._tied(80)(table([sets[0], np.arange(union + 1)])).num_rows == 0


def test_components_step_by_step(spark, monkeypatch):
    edges = spark.createDataFrame([(i, i + 1) for i in range(0, 40)] + [(100, j) for j in range(101, 130)] + [(7, 7)], "a long, b long")
    monkeypatch.setattr("spangrid.llm.components.FEW", 0)
    got = {r["node"]: r["component"] for r in components(edges).collect()}
    assert got == {i: 0 for i in range(41)} | {j: 100 for j in range(100, 130)}


def test_toxicity(docs, labels, nothing, spark):
    out = {r["doc_id"]: r for r in toxicity.score_documents(docs, labels).collect()}
    assert all(0 <= r["score"] <= 1 for r in out.values())
    assert all(r["held_out"] == (i is None or zlib.crc32(str(i).encode()) % 5 == 0) for i, r in out.items())
    assert toxicity.score_documents(nothing, labels).isEmpty()
    assert toxicity.score_documents(docs, labels.limit(0)).filter("score <> 0").isEmpty()
    assert toxicity.reject(docs, labels).columns == docs.columns


def test_toxicity_learns_held_out(spark):
    d = "/root/testdata/sf0.1"
    labels = spark.read.parquet(f"{d}/labels.parquet")
    out = toxicity.score_documents(spark.read.parquet(f"{d}/documents.parquet"), labels).filter("held_out").join(labels, "doc_id").select("predicted", "toxic").toPandas()
    assert (out["predicted"] == out["toxic"]).mean() > 0.96
    assert ((out["predicted"] == 1) & (out["toxic"] == 0)).sum() <= 0.01 * len(out)


def test_forward_backward():
    """Marginals of the field against the sum over all label sequences."""
    import itertools

    import pyarrow as pa

    from spangrid.llm.flat import texts_of

    field = toxicity.Field()
    rng = np.random.default_rng(1)
    field.w, field.edge = rng.normal(size=1 << toxicity.BITS), rng.normal(size=(2, 2))
    k = toxicity.Tokens(next(texts_of(pa.array(["alpha beta gamma delta eps. one two"]))))
    z = field.bias + sum(field.w[f] for f in k.features)
    for lo, hi in ((0, 5), (5, 7)):
        total, on = 0.0, np.zeros(hi - lo)
        for y in itertools.product((0, 1), repeat=hi - lo):
            p = math.exp(sum(z[lo + i] for i, v in enumerate(y) if v) + sum(field.edge[a, b] for a, b in zip(y, y[1:])))
            total, on = total + p, on + p * np.array(y)
        assert np.allclose(field.marginals(k)[lo:hi], on / total)


def test_rangejoin(spark, monkeypatch, sf):
    rng = np.random.default_rng(4)
    base = rng.normal(size=(60, 8))
    rows = [(i, [float(x) for x in base[i % 60] + 0.12 * rng.normal(size=8) * (i >= 60)]) for i in range(400)]
    odd = [(-1, None), (-2, []), (-3, [0.0] * 8), (-4, [float("nan")] * 8), (-5, [1.0] * 8), (-5, [1.0] * 8), (-6, [2.0] * 8), (-7, [1.0, None]), (None, [1.0] * 8), (-8, [1.0] * 7), (-9, [float("inf")] + [1.0] * 7)]
    for name, v in (("CELL", 60), ("HOMES", 16), ("PROBES", 40)):
        monkeypatch.setattr(rangejoin, name, v)
    ids = [i for i, _ in rows] + [-5, -5, -6]
    u = np.array([v for _, v in rows] + [[1.0] * 8] * 3)
    u /= np.linalg.norm(u, axis=1)[:, None]
    hit = u @ u.T >= 0.95
    np.fill_diagonal(hit, False)
    label = np.array(ids)
    while True:
        new = np.array([min([label[i], *label[hit[i]]]) for i in range(len(ids))])
        if (new == label).all():
            break
        label = new
    want = [(i, int(n), int(c), bool(c == i)) for i, n, c in zip(ids, hit.sum(1), label)] + [(i, 0, i, True) for i in (-1, -2, -3, -4, -7, None, -8, -9)]
    df = spark.createDataFrame(rows + odd, "vec_id long, embedding array<double>").withColumn("n_links", F.lit("clash"))
    same([tuple(r) for r in rangejoin.near_vectors(df).collect()], want)
    assert rangejoin.near_vectors(df.limit(0)).isEmpty()


def test_rangejoin_in_rounds(spark, monkeypatch):
    """No round moves more than one copy of the vectors and one slice's, whatever all rounds move, and single precision stays so."""
    rng = np.random.default_rng(5)
    x = (rng.normal(size=(300, 12)) + 2 * rng.normal(size=(20, 12))[rng.integers(0, 20, 300)]).astype(np.float32)
    for name, v in (("CELL", 30), ("HOMES", 500), ("PROBES", 500), ("COPIES", 1), ("LEAST_BYTES", 0)):
        monkeypatch.setattr(rangejoin, name, v)
    moved, sent, widths = [], rangejoin._sent, set()

    def spied(dealt, *more):
        out = sent(dealt, *more)
        moved.append(out.count())
        widths.update(r[0] for r in out.selectExpr("length(v)").distinct().collect())
        return out

    monkeypatch.setattr(rangejoin, "_sent", spied)
    got = sorted(tuple(r)[:2] for r in rangejoin.near_vectors(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")).collect())
    u = x.astype(float)
    u /= np.linalg.norm(u, axis=1)[:, None]
    hit = u @ u.T >= 0.95
    np.fill_diagonal(hit, False)
    assert hit.any() and got == [(i, int(n)) for i, n in enumerate(hit.sum(1))]
    assert len(moved) > 1 and sum(moved) > 300 and max(moved) <= 600 and widths == {48}


def test_rangejoin_of_mixed_lengths(spark):
    """Vectors link within their own length, whichever length is most frequent."""
    rows = [(i, [1.0, 0.01 * i, 0.0]) for i in range(5)] + [(10 + i, [0.0, 1.0, 0.01 * i, 0.0]) for i in range(3)] + [(20, [1.0, 0.0]), (21, [1.0, 0.0]), (22, [0.0, 1.0]), (30, [1.0] * 9), (31, [1.0] * 9)]
    got = [tuple(r) for r in rangejoin.near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()]
    same(got, [(i, 4, 0, i == 0) for i in range(5)] + [(10 + i, 2, 10, i == 0) for i in range(3)] + [(20, 1, 20, True), (21, 1, 20, False), (22, 0, 22, True), (30, 1, 30, True), (31, 1, 30, False)])


@pytest.mark.parametrize("together", [2, 64])
def test_suffixes(spark, awkward, monkeypatch, together, nothing):
    monkeypatch.setattr(suffixes, "TOGETHER", together)
    rng = np.random.default_rng(2)
    part = "".join(rng.choice(list("abcdefgh "), 60))
    rows = [(100 + i, str(rng.random()) + part[rng.integers(20) : 40 + rng.integers(20)] + str(rng.random())) for i in range(80)] + [(300, part), (301, part), (302, part[:40] + "q"), (303, "z" + part[1:40] + "q")]
    df = awkward.unionByName(spark.createDataFrame(rows, "doc_id long, text string"))
    raw = [(r["doc_id"], (r["text"] or "").encode()) for r in df.collect()]
    n = 40
    seen = collections.Counter(x[i : i + n] for _, x in raw for i in range(len(x) - n + 1))
    want = []
    for i, x in raw:
        gone = np.zeros(len(x) + 1, int)
        for q in range(len(x) - n + 1):
            if seen[x[q : q + n]] > 1:
                gone[q] += 1
                gone[q + n] -= 1
        gone = np.cumsum(gone)[: len(x)] > 0
        runs = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        want.append((i, len(x), int(gone.sum()), runs, sha(bytes(np.frombuffer(x, np.uint8)[~gone]))))
    same([tuple(r) for r in suffixes.remove_repeats(df, n, 16).drop("kept").collect()], want)
    assert suffixes.remove_repeats(nothing).isEmpty()


def test_multikey_order():
    rng = np.random.default_rng(3)
    keys = [rng.integers(0, 4, 500).astype(np.uint64) for _ in range(3)]
    order, tie = suffixes.multikey_order(*keys)
    rows = list(zip(*[k[order].tolist() for k in keys]))
    assert rows == sorted(rows) and tie.tolist() == [False] + [a == b for a, b in zip(rows, rows[1:])]


def test_quality(docs, local, labels, nothing):
    got = {}
    for r in quality.judge(docs, labels).collect():
        got[r["doc_id"]] = tuple(r)[1:7]
    for i, x in local:
        x = x or ""
        w = WORD.findall(x)
        five = collections.Counter(tuple(w[j : j + 5]) for j in range(len(w) - 4))
        cover = {j + d for j in range(len(w) - 4) if five[tuple(w[j : j + 5])] > 1 for d in range(5)}
        lines, dup = set(), 0
        for line in x.split("\n"):
            if WORD.search(line):
                dup += line in lines
                lines.add(line)
        assert got[i] == (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in x), dup, len(cover), len(w) < 10 or 100 * len(cover) > 20 * len(w))
    assert quality.judge(docs, labels).filter("base_failed and kept").isEmpty()
    assert quality.judge(docs, labels.limit(0)).filter("kept = base_failed").isEmpty()
    assert quality.judge(nothing, labels).isEmpty()


def test_sharding(docs, nothing, local):
    out = sharding.shard_documents(docs, 24).toPandas()
    assert len(out) == len(local) and set(out["law"]) == {"rows"}
    n = out.groupby("shard")["slot"].agg(["count", "max", "nunique"])
    assert n["count"].max() - n["count"].min() <= 1 and (n["max"] + 1 == n["count"]).all() and (n["nunique"] == n["count"]).all()
    want = collections.Counter((len((x or "").encode()) + 8, zlib.crc32((x or "").encode())) for _, x in local)
    assert collections.Counter(zip(out["size"], out["text_crc32"])) == want
    assert sharding.shard_documents(nothing, 24).isEmpty()


def test_sharding_places_equal_rows_apart(spark):
    """Copies of one row are dealt like any rows: over all shards, and not side by side."""
    rows = spark.range(0, 4800, 1, 4).select(F.when(F.col("id") < 1600, 7).otherwise(F.col("id")).alias("b"))
    out = sharding.shuffle_into_shards(rows, 24).toPandas()
    hot = out[out["b"] == 7].groupby("shard")["slot"].agg(["count", "std"])
    assert len(hot) == 24 and hot["count"].between(35, 105).all() and hot["std"].min() > 25
    assert sorted(out["b"]) == sorted(r["b"] for r in rows.collect())


def test_hypergeometric_of_any_size():
    rng = np.random.default_rng(2)
    good, bad, n = 10**11 // 24, 10**11 - 10**11 // 24, 200_000
    x = np.array([sharding.hypergeometric(rng, good, bad, n) for _ in range(2000)])
    p = good / (good + bad)
    assert abs(x.mean() - n * p) < 4 * math.sqrt(n * p * (1 - p) / 2000) and 0.85 < x.var() / (n * p * (1 - p)) < 1.15
    assert sharding._draw(rng, np.array([3 * 10**9, 1, 2 * 10**9, 0]), 5 * 10**9 + 1).tolist() == [3 * 10**9, 1, 2 * 10**9, 0]


def test_communication_matrix():
    m = sharding.communication_matrix(np.array([5, 0, 17, 3]), 4, 1)
    assert m.sum(1).tolist() == [5, 0, 17, 3] and sorted(m.sum(0)) == [6, 6, 6, 7]


def test_secrets(docs, local, labels, nothing):
    out = secrets.spans_of_documents(docs, labels)
    got = collections.Counter((r["doc_id"], r["n_assign"], r["n_access"], r["n_hex"], r["base_sha256"]) for r in out.collect())
    want = collections.Counter()
    for i, x in local:
        x = x or ""
        found = [(m.start(), 0, m.end()) for m in re.finditer(secrets.ASSIGN, x) if len(m[2]) >= 8]
        found += [(m.start(), 1, m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", x) if len(m[0]) >= 16] + [(m.start(), 2, m.end()) for m in re.finditer(r"[0-9a-f]+", x) if len(m[0]) >= 32]
        n = collections.Counter(k for _, k, _ in found)
        want[(i, n[0], n[1], n[2], sha(",".join(f"{secrets.KINDS[k]}:{a}:{b}" for a, k, b in sorted(found)).encode()))] += 1
    assert got == want
    spans = {r["doc_id"]: r["spans"] for r in out.collect()}
    at = dict(local)[-12].index("aX9bQ2zL0pRt7UvW3kYm")
    assert f"random:{at}:{at + 20}" in spans[-12]
    clean = {r["doc_id"]: r["text"] for r in secrets.redact(docs, labels).collect()}
    assert "hunter22" not in clean[-12] and "[secret]" in clean[-12] and clean[-1] is None
    assert secrets.spans_of_documents(nothing, labels).isEmpty()
    plan = out._jdf.queryExecution().toString()
    assert "Python" not in plan and "Pandas" not in plan and "Arrow" not in plan


def test_clashing_names_repeated_rows_and_empty_tables(docs, labels, local):
    """Columns named as an operator's own come through; a repeated row goes once; a table without rows stays one."""
    names = ["_assign", "_access", "_hex", "_base", "_added", "_random", "_n", "_d", "_k", "n", "k", "key", "copy", "rate", "kept", "gone", "spans", "x0", "c0", "_may"]
    wide = docs.drop("score").withColumns({c: F.concat(F.lit(c), F.col("doc_id").cast("string")) for c in names}).withColumns({"lang": F.lit("en"), "component_id": F.lit(1)})
    was = {(r["doc_id"], r["text"]) for r in wide.collect()}
    for f in (lambda d: secrets.redact(d, labels), lambda d: mixing.resample(d, labels, {"en": 1.0}), lambda d: minhash.keep_one(d, 5), lambda d: toxicity.reject(d, labels)):
        out = f(wide)
        assert out.columns == wide.columns
        rows = out.collect()
        assert rows and all(r[c] == (None if r["doc_id"] is None else f"{c}{r['doc_id']}") for r in rows for c in names)
        assert {r["doc_id"] for r in rows} <= {i for i, _ in was}
        assert f(wide.limit(0)).isEmpty() and f(wide.limit(0)).columns == wide.columns
    kept = [r["doc_id"] for r in minhash.keep_one(wide, 5).collect()]
    assert kept.count(-5) == 1 and kept.count(-3) == 0 and [i for i, _ in local].count(-5) == 2
    twice = docs.filter("doc_id = -6").unionByName(docs.filter("doc_id = -6")).unionByName(docs.filter("doc_id is null")).unionByName(docs.filter("doc_id is null"))
    assert sorted(str(r["doc_id"]) for r in minhash.keep_one(twice, 5).collect()) == ["-6", "None", "None"]


def test_secret_model(spark, docs, labels):
    model = secrets.fit(docs, labels)
    held = secrets.random_strings(spark, 200, seed=9).select((secrets.ratio(F.col("s"), model) >= secrets.LEAST_RATIO).alias("hit"))
    assert held.filter("hit").count() >= 0.97 * held.count()


@pytest.mark.parametrize("shared", [5, 1 << 16])
def test_suffixtree(docs, local, nothing, monkeypatch, shared):
    monkeypatch.setattr(suffixtree, "MOST_SHARED", shared)
    count, rows = collections.Counter(), []
    for i, x in local:
        w = [*WORD.findall((x or "").translate(LOW)), None]
        held = i is not None and zlib.crc32(str(i).encode()) % 10 == 0
        rows.append((i, held, w))
        if not held:
            count.update(w)
    n, v = sum(count.values()), len(count)
    want = [(i, h, len(w), sum(count[t] > 0 for t in w), n, sum(math.log10((count[t] + 0.1) / (n + 0.1 * (v + 1))) for t in w)) for i, h, w in rows]
    out = suffixtree.score_documents(docs).toPandas()
    same([(None if r.doc_id != r.doc_id else int(r.doc_id), r.held_out, r.n_tokens, r.n_known, r.train_tokens, r.base_score) for r in out.itertuples()], want)
    held = out[out["held_out"]]
    assert held["score"].sum() > held["base_score"].sum()
    assert suffixtree.score_documents(nothing).isEmpty()


@pytest.mark.parametrize("shared", [0, 1 << 20])
def test_suffixtree_learns_word_order(spark, monkeypatch, shared):
    """Words of one class and equal counts, so only tokens' order tells texts apart; brute force gives the scores."""
    monkeypatch.setattr(suffixtree, "SHARED_STATES", shared)
    least, pair, depth = suffixtree.LEAST_COUNT, suffixtree.LEAST_PAIR, suffixtree.TOKENS
    held = [i for i in range(600) if zlib.crc32(str(i).encode()) % 10 == 0]
    odd = {held[0]: "xa ya za wa", held[1]: "ya xa wa za", held[2]: "xa ya", held[3]: "za never xa ya", held[4]: None}
    rows = [(i, odd.get(i, ("xa ya za wa", "za wa xa ya", "xa ya wa za xa ya")[i % 3])) for i in range(600)]
    out = {r["doc_id"]: r for r in suffixtree.score_documents(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    good, swapped = out[held[0]], out[held[1]]
    assert abs(good["base_score"] - swapped["base_score"]) < 1e-9 and good["score"] > swapped["score"] + 1

    train = [["<", *(t or "").split(), ">"] for i, t in rows if i not in held]
    n = collections.Counter(tuple(w[j - d : j + 1]) for w in train for j in range(1, len(w)) for d in range(min(j, depth) + 1))
    words = {g[0]: c for g, c in n.items() if len(g) == 1}
    total = sum(words.values())
    follow = collections.defaultdict(dict)
    for g, c in n.items():
        if len(g) > 1:
            follow[g[:-1]][g[-1]] = c
    follow = {g: c for g, c in follow.items() if sum(c.values()) >= least}

    def p(w, g):
        if not g:
            return (words.get(w, 0) + 0.1) / (total + 0.1 * (len(words) + 1))
        own = {k: v for k, v in follow[g].items() if v >= pair}
        every = sum(follow[g].values()) + len(own)
        return (own.get(w, 0) + (every - sum(own.values())) * p(w, g[1:])) / every

    def diverges(g):
        own, size = {k: v for k, v in follow[g].items() if v >= pair}, sum(follow[g].values())
        up = {k: p(k, g[1:]) for k in own}
        rest, cells = size - sum(own.values()), len(own) + (size > sum(own.values()))
        stat = sum(v * math.log(v / size / up[k]) for k, v in own.items()) + (rest * math.log(rest / size / (1 - sum(up.values()))) if rest else 0)
        return 2 * stat > cells + suffixtree.DEVIATIONS * math.sqrt(2 * cells)

    states = {g[j:] for g in follow if diverges(g) for j in range(len(g))}
    assert {len(g) for g in states} >= {1, 2}
    for i in held[:3]:
        w = ["<", *odd[i].split(), ">"]
        want = 0
        for j in range(1, len(w)):
            context = max((tuple(w[j - d : j]) for d in range(1, min(j, depth) + 1) if tuple(w[j - d : j]) in states), key=len)
            want += math.log10(p(w[j], context))
        assert abs(out[i]["score"] - want) < 1e-6


def test_tree_is_a_distribution():
    rng = np.random.default_rng(5)
    a = suffixtree.ALPHABET
    codes = np.unique(rng.integers(0, a**4, 3000))
    tree = suffixtree.Tree(codes, rng.integers(1, 90, len(codes)).astype(float))
    assert np.allclose((10.0 ** tree.log.astype(np.float64)).sum(1), 1, atol=1e-4)
    assert tree.state.shape == (a**3,) and tree.state.max() < len(tree.log)


def test_mixing(spark, sf, labels, nothing, monkeypatch):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    odd = docs.limit(1).withColumns({"doc_id": F.lit(-1).cast("long"), "text": F.lit(None).cast("string"), "lang": F.lit(None).cast("string")})
    out = mixing.mix_documents(docs.unionByName(odd), labels, {"en": 0.4, "de": 0.2, "es": 0.2, "fr": 0.2}).toPandas()
    names = [c[2:] for c in out.columns if c.startswith("p_")]
    assert (out["rate"] >= 0).all() and np.allclose(out[[f"p_{c}" for c in names]].sum(axis=1), 1)
    share = {c: (out["rate"] * out["n_tokens"] * out[f"p_{c}"]).sum() / out["n_tokens"].sum() for c in names}
    assert all(abs(share[c] - (0.4 if c == "en" else 0.2)) < 0.01 for c in share)
    many = docs.select("doc_id", "text", F.concat("lang", "doc_id").alias("domain"))
    with monkeypatch.context() as m:
        m.setattr(mixing.Softmax, "fit", lambda self, *a, **b: self)
        m.setattr("spangrid.llm.hashed.BITS", 4)
        got = mixing.learn(many, labels, [r["domain"] for r in many.select("domain").collect()]).classes
    assert set(got) == {r["domain"] for r in many.join(labels, "doc_id").collect()} and len(got) > 64  # every domain that a labelled document has
    rare = mixing.mix_documents(docs, labels, {"es": 1.0})
    assert [c for c in rare.columns if c.startswith("p_")] == ["p_es", "p_other"]
    one = mixing.mix_documents(docs, labels.limit(0), {"en": 1.0})
    assert one.filter("rate <> 1 or copies <> 1").isEmpty()
    assert mixing.resample(docs, labels, {"en": 1.0}).columns == docs.columns


def test_pipeline(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "near_duplicates", "secrets", "mixing", "encoding"]
    stage = dict(corpus_pipeline.STAGES)
    kept = stage["toxicity"](spark, docs, sf)
    bad = {r["doc_id"] for r in toxicity.score_documents(docs, labels).filter("predicted = 1").collect()}
    assert {r["doc_id"] for r in kept.select("doc_id").collect()} == {r["doc_id"] for r in docs.select("doc_id").collect()} - bad
    near = {r["doc_id"] for r in minhash.near_duplicates(docs, 5).filter("kept").collect()}
    assert {r["doc_id"] for r in stage["near_duplicates"](spark, docs, sf).select("doc_id").collect()} == near
    step = docs
    for name, f in corpus_pipeline.STAGES:
        step = f(spark, step, sf)
    whole = corpus_pipeline.run(spark, sf)
    assert whole.columns == ["doc_id", "source", "ids", "text"] == step.columns
    same([(r["doc_id"], r["source"], str(r["ids"]), r["text"]) for r in whole.collect()], [(r["doc_id"], r["source"], str(r["ids"]), r["text"]) for r in step.collect()])
    assert {r["doc_id"] for r in whole.collect()} <= near - bad
    last = stage["encoding"](spark, docs, sf)
    assert last.join(docs.select("doc_id", F.col("text").alias("was")), "doc_id").filter("text <> was").isEmpty()
    for name in ("toxicity", "near_duplicates", "secrets", "mixing"):
        assert stage[name](spark, docs, sf).columns == docs.columns
