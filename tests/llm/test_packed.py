import pickle
import time

import numpy as np
from pyspark.sql import functions as F

from spangrid import storage
from spangrid.llm import packed, suffixtree, tables


def test_pieces_give_back_their_columns():
    rng = np.random.default_rng(3)
    keys = np.sort(rng.integers(0, 1 << 63, 5000).astype(np.uint64) * np.uint64(2))
    moves, few = rng.integers(-900, 900, 5000), rng.integers(0, 200, 5000).astype(np.uint32)
    piece = packed.pack(packed.steps(keys), packed.signed(moves), few, rng.random(3), np.zeros(0, np.int64))
    a, b, c, d, e = packed.unpack(piece)
    assert (np.cumsum(a) == keys).all() and (packed.unsigned(b) == moves).all() and (c == few).all() and len(d) == 3 and not len(e)
    assert len(piece) < 5000 * 11
    own = list(packed.cut(packed.bucket(keys, 3)))
    assert [i for i, _ in own] == sorted({int(k) >> 61 for k in keys}) and sum(s.stop - s.start for _, s in own) == 5000
    assert list(packed.cut(packed.bucket(keys, 0))) == [(0, slice(0, 5000))] and not list(packed.cut(keys[:0]))


def test_places():
    rng = np.random.default_rng(4)
    for n in (0, 1, 5000):
        keys = np.unique(np.concatenate([rng.integers(0, 1 << 63, n).astype(np.uint64) * np.uint64(2), np.arange(min(n, 50), dtype=np.uint64)]))
        asked = np.concatenate([keys, keys + np.uint64(1), np.array([0, 2**64 - 1], np.uint64)])
        k, hit = suffixtree.Places(keys).find(asked)
        assert (hit == np.isin(asked, keys)).all() and (keys[k[hit]] == asked[hit]).all() and (not n or k.max() <= len(keys))


def test_suffixtree_in_many_pieces(spark, monkeypatch):
    """Scores do not depend on how many pieces leave a task, which words are shared, or into how many buckets pieces go; a few hundred rows move, not one for each pair."""
    texts = ["xa ya za wa", "za wa xa ya nu", "xa ya wa za xa ya", "", None, "rare xa ya"]
    rows = [(i % 560, texts[i % 560 % 6]) for i in range(600)] + [(None, "xa ya")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartitionByRange(3, F.col("doc_id")).persist()
    names = ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"]

    def scores():
        out = suffixtree.score_documents(docs).toPandas()[names].sort_values(["doc_id", "score"])
        assert len(out) == 601
        return out.to_numpy(dtype=float)

    want = scores()
    monkeypatch.setattr(suffixtree, "BUCKET", 64)
    monkeypatch.setattr(suffixtree, "HAND_ON", 50)
    monkeypatch.setattr(suffixtree, "MOST_TEXTS", 20)
    monkeypatch.setattr(suffixtree, "MOST_SHARED", 2)
    monkeypatch.setattr(suffixtree, "SHARED_STATES", 0)
    assert np.allclose(scores(), want, rtol=0, atol=1e-6, equal_nan=True)
    docs.unpersist()


def test_shared_keys_travel_packed():
    """What is shared with tasks is one file on each executor's disk, so keys go as differences and where they begin is found anew."""
    keys = np.unique(np.random.default_rng(5).integers(0, 1 << 63, 100_000).astype(np.uint64) * np.uint64(2))
    places = suffixtree.Places(keys)
    sent = pickle.dumps(places)
    assert len(sent) < 8 * len(keys)
    got = pickle.loads(sent)
    assert (got.keys == places.keys).all() and (got.start == places.start).all() and got.find(keys)[1].all()
    bits = object.__new__(suffixtree.Bits)
    bits.log, at = 22, np.unique(keys >> np.uint64(42))
    bits.bits = np.packbits(np.isin(np.arange(1 << 22), at.astype(np.int64)), bitorder="little").view(np.uint64)
    sent = pickle.dumps(bits)
    assert len(sent) < bits.bits.nbytes // 2
    got = pickle.loads(sent)
    assert got.has(keys).all() and got.has(np.arange(1 << 22, dtype=np.uint64) << np.uint64(42)).sum() == len(at)


def test_suffixtree_asks_in_rounds(spark, monkeypatch):
    """Texts ask in rounds, each over before the next begins; only states and words that are not shared are listed, once; of what is written only scores stay."""
    docs = spark.createDataFrame([(i, ("xa ya za wa", "za wa xa ya nu", f"xa ya rare{i}")[i % 3]) for i in range(600)], "doc_id long, text string").persist()
    labels, gone = [], []

    def written(df, label):
        out = storage.written(df, label)
        labels.append((label, out.count(), out._spangrid_at))
        return out

    monkeypatch.setattr(suffixtree, "written", written)
    monkeypatch.setattr(suffixtree, "forget", lambda *tables: gone.extend(t._spangrid_at for t in tables) or storage.forget(*tables))
    whole = suffixtree.score_documents(docs).toPandas().sort_values("doc_id")
    assert [n for label, n, _ in labels if label == "scores"] == [600]
    labels.clear(), gone.clear()
    monkeypatch.setattr(suffixtree, "BUCKET", 8)
    out = suffixtree.score_documents(docs).toPandas().sort_values("doc_id")
    each = [n for label, n, _ in labels if label == "scores"]
    assert len(each) == suffixtree._rounds(int(out["train_tokens"].iloc[0])) > 2 and sum(each) == 600 and max(each) < 400
    assert [label for label, _, _ in labels].count("lists") == 1
    assert {at for label, _, at in labels if label != "scores"} == set(gone)
    assert np.allclose(out["score"], whole["score"], rtol=0, atol=1e-6) and (out["n_known"].to_numpy() == whole["n_known"].to_numpy()).all()
    docs.unpersist()


def test_suffixtree_drops_shuffle_files(spark, monkeypatch):
    """Shuffle files go as each query ends, not when the driver happens to collect its garbage; the session's setting comes back."""
    docs = spark.createDataFrame([(i, ("xa ya za wa", "za wa xa ya nu", f"xa ya rare{i}")[i % 3]) for i in range(600)], "doc_id long, text string")
    manager = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()

    def left():
        return {f.split("/")[-1] for f in manager.getAllFiles().mkString("\n").split("\n") if "/shuffle_" in f}

    before, after, set_ = left(), [], spark.conf.get(tables.DROP_FILES)

    def release(_):  # instead of a collection, a while for the executors' answers
        for _ in range(50):
            if not left() - before:
                break
            time.sleep(0.1)
        after.append(left() - before)

    monkeypatch.setattr(suffixtree, "release", release)
    suffixtree.score_documents(docs).toPandas()
    assert len(after) > 5 and not any(after)
    assert spark.conf.get(tables.DROP_FILES) == set_
