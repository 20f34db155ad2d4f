"""Operators on small fixtures against plain Python, and their edge cases."""

import hashlib
import io
import math
import random
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import public_tokenizers
from crowding.llm import bpe_automaton, elias_fano, jaccard_join, maxent_lm, media, poisson_mix, simhash, token_counts, toxicity, warc
from crowding.llm.common import keyed, scratch

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
WORD = str(public_tokenizers.path("word_bpe_49k.json"))
BYTE = str(public_tokenizers.path("byte_bpe_50k.json"))


def docs(spark, texts, start=0):
    return spark.createDataFrame([(start + i, t, "en" if i % 3 else "fr", f"s{i % 2}", None if t is None else len(t)) for i, t in enumerate(texts)], DOCS)


def odd(spark):
    """Nulls in every column, empty, repeated and long rows, and columns whose names clash with inner ones."""
    rows = [(1, "the cat sat on the mat", "en", "a", 22), (1, "the cat sat on the mat", "en", "a", 22), (None, "no id here", None, None, None), (2, None, "en", "a", None), (3, "", "en", "b", 0), (4, " \t\n", "en", "b", 3), (5, "é漢🙂 <|endoftext|> 'tis x" * 500, "fr", "b", 1)]
    return spark.createDataFrame(rows, DOCS).withColumn("key", F.lit("clash")).withColumn("fp", F.lit(1)).withColumn("n", F.lit(2)).withColumn("shard", F.lit("x"))


def empty(spark):
    return spark.createDataFrame([], DOCS)


# 1


def test_rollup_batches(spark):
    r = token_counts.TokenRollup(spark, scratch(spark, "rollup"))
    c = token_counts.count_tokens(docs(spark, ["a b c", "a b c", "d, e"]))
    one = token_counts.change(c, 1, "words-1", "tokens_0")
    assert r.apply("b1", one) and not r.apply("b1", one)
    total = lambda: {(x["source"], x["lang"]): (x["n_docs"], x["n_tokens"]) for x in r.totals().collect()}
    assert total() == {("s0", "fr"): (1, 3), ("s1", "en"): (1, 3), ("s0", "en"): (1, 2)}
    assert r.apply("b2", token_counts.change(token_counts.later_copies(c), -1, "words-1", "tokens_0"))
    assert total() == {("s0", "fr"): (1, 3), ("s0", "en"): (1, 2)}
    before = total()
    r.fold()
    assert total() == before and not r.apply("b2", one) and r.committed() == ["b1", "b2"]
    assert r.vacuum(0) >= 3 and total() == before and r.vacuum(0) == 0


def test_rollup_many_batches_and_folds(spark):
    r = token_counts.TokenRollup(spark, scratch(spark, "rollup"))
    one = spark.createDataFrame([("s", "en", "words-1", 1, 5, 9)], token_counts.SCHEMA).coalesce(1)
    for i in range(100):
        assert r.apply(f"batch-{i:03d}", one)
        if i == 60:
            assert r.fold()
            r.vacuum(0)
    assert r.fold() and not r.fold()
    assert tuple(r.totals().first()) == ("s", "en", "words-1", 100, 500, 900)
    assert len(r.committed()) == 100 and not r.apply("batch-017", one)
    r.vacuum(0)
    assert tuple(r.totals().first())[3:] == (100, 500, 900)


def test_rollup_survives_crashes_and_other_writers(spark, monkeypatch):
    root = scratch(spark, "rollup")
    a, b = token_counts.TokenRollup(spark, root), token_counts.TokenRollup(spark, root)
    one = spark.createDataFrame([("s", "en", "words-1", 1, 5, 9)], token_counts.SCHEMA).coalesce(1)
    n = lambda: tuple(a.totals().first())[3:]
    assert a.apply("x", one) and b.apply("y", one) and not a.apply("y", one) and not b.apply("x", one) and n() == (2, 10, 18)

    def crash(*args):
        raise RuntimeError("lost")

    for job in (lambda: a.apply("z", one), a.fold):  # between folder and manifest
        with monkeypatch.context() as m:
            m.setattr(a, "_create", crash)
            with pytest.raises(RuntimeError):
                job()
        assert n() == (2, 10, 18) and b.committed() == ["x", "y"]
    # a writer that looked before another one committed the same id, or another id
    for mine, theirs, won in (("z", "z", False), ("v", "w", True)):
        look = a._version
        with monkeypatch.context() as m:

            def late():
                m.undo()
                v = look()
                assert b.apply(theirs, one)
                return v

            m.setattr(a, "_version", late)
            assert a.apply(mine, one) is won
    assert n() == (5, 25, 45) and a.committed() == ["v", "w", "x", "y", "z"]
    # two folds of the same batches: one wins
    write = a._write
    with monkeypatch.context() as m:
        m.setattr(a, "_write", lambda df: (m.undo(), write(df), b.fold())[1])
        assert a.fold() is False
    assert n() == (5, 25, 45) and a.vacuum(0) and n() == (5, 25, 45)


def test_later_copies_of_large_groups(spark, monkeypatch):
    d = docs(spark, ["same text"] * 30 + ["other"] * 3 + [f"t{i}" for i in range(20)] + [None, ""])
    c = token_counts.count_tokens(d)
    want = [*range(1, 30), 31, 32, 54]
    assert sorted(r["doc_id"] for r in token_counts.later_copies(c).collect()) == want
    monkeypatch.setattr(token_counts, "HEAVY", 5)
    assert sorted(r["doc_id"] for r in token_counts.later_copies(c).collect()) == want


def test_rollup_odd_rows(spark):
    out = token_counts.maintain(odd(spark), token_counts.TokenRollup(spark, scratch(spark, "rollup"))).collect()
    assert sum(r["n_docs"] for r in out) == 6  # an empty text stands for the null one too
    assert token_counts.maintain(empty(spark), token_counts.TokenRollup(spark, scratch(spark, "rollup"))).count() == 0


# 2


def bmp(rgb):
    h, w, _ = rgb.shape
    stride = (w * 3 + 3) // 4 * 4
    rows = b"".join(r[:, ::-1].tobytes().ljust(stride, b"\0") for r in rgb[::-1])
    import struct

    return b"BM" + struct.pack("<IHHI", 54 + len(rows), 0, 0, 54) + struct.pack("<IiiHHIIiiII", 40, w, h, 1, 24, 0, len(rows), 0, 0, 0, 0) + rows


def test_image_formats():
    rng = np.random.default_rng(0)
    g, c = rng.integers(0, 256, (5, 7), dtype=np.uint8), rng.integers(0, 256, (4, 3, 3), dtype=np.uint8)
    assert (media.decode(media.encode_pgm(g)) == g).all()
    assert (media.decode(b"P2 # c\n7 5 255\n" + " ".join(map(str, g.ravel())).encode()) == g).all()
    assert (media.decode(b"P6\n3 4\n255\n" + c.tobytes()) == c).all()
    bits = rng.integers(0, 2, (3, 11), dtype=np.uint8)
    assert (media.decode(b"P4\n11 3\n" + np.packbits(bits, axis=1).tobytes()) == bits).all()
    assert (media.decode(b"P1\n11 3\n" + " ".join(map(str, bits.ravel())).encode()) == bits).all()
    wide = rng.integers(0, 65536, (2, 2)).astype(np.uint16)
    assert (media.decode(b"P5 2 2 65535\n" + wide.astype(">u2").tobytes()) == wide).all()
    assert (media.decode(bmp(c)) == c).all()
    for bad in (b"", b"P5\n9 9\n255\nxx", b"BMxx", b"GIF89a"):
        with pytest.raises((ValueError, IndexError)):
            media.decode(bad)


def test_resize_is_area_mean_and_npy_is_numpys():
    rng = np.random.default_rng(1)
    a = rng.random((12, 8))
    assert np.allclose(media.resize(a, 3, 4), a.reshape(3, 4, 4, 2).mean(axis=(1, 3)))
    assert math.isclose(media.resize(a, 5, 3).mean(), a.mean())
    for x in (a, a.astype(np.uint8), np.arange(3)):
        assert (np.load(io.BytesIO(media.npy_bytes(x))) == x).all() and (media.read_npy(media.npy_bytes(x))[0] == x).all()
    assert (media.untile(list(media.tiles(a, 5, 3))) == a).all()


def test_media_tiles(spark):
    img = media.encode_pgm(np.arange(64, dtype=np.uint8).reshape(8, 8))
    df = spark.createDataFrame([(1, img), (2, None), (3, b"junk"), (4, img)], "pic long, data binary")
    tiled = media.media_tiles(df, "pic", "data", 4)
    rows = tiled.collect()
    assert Counter(r["id"] for r in rows) == {1: 4, 2: 1, 3: 1, 4: 4}
    assert len({r["difference_hash"] for r in rows if r["id"] in (1, 4)}) == 1
    root = scratch(spark, "tiles")
    paths = media.write_tiles(tiled, root).collect()
    assert len(paths) == 8 and np.load(paths[0]["path"].removeprefix("file:").replace("//", "/", 1)).shape == (4, 4)


def test_carried_text():
    for t in (b"", b"x", b"y" * 64, b"z" * 70_001):
        n, size, sha, crc, stored, _, _, _ = media._carry(t)
        want = t + bytes(-len(t) % 64 if t else 64)
        assert (n, size, sha, crc) == (len(t), len(want), hashlib.sha256(want).hexdigest(), zlib.crc32(want[-64:])) and stored > size


def test_media_query_on_odd_rows(spark, tmp_path):
    """Every column of the query against plain Python, on nulls, empty, long and repeated texts."""
    long = "é漢🙂 line\n" * 40_000
    rows = [(1, "abc"), (1, "abc"), (None, "x" * 64), (2, None), (3, ""), (4, long), (5, "y" * 65)]
    spark.createDataFrame(rows, "doc_id long, text string").withColumn("feature", F.lit("clash")).write.parquet(f"{tmp_path}/documents.parquet")
    got = media.op2_media_columns(spark, str(tmp_path)).collect()
    want = Counter()
    for i, t in rows:
        raw = (t or "").encode()
        pay = raw + bytes(-len(raw) % 64 if raw else 64)
        want[i, len(raw), len(pay), hashlib.sha256(pay).hexdigest(), zlib.crc32(pay[-64:])] += 1
    assert Counter((r["doc_id"], r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) for r in got) == want
    assert len({(r["media_bytes"], r["media_sha256"], r["feature"]) for r in got if r["doc_id"] in (2, 3)}) == 1
    spark.createDataFrame([], "doc_id long, text string").write.parquet(f"{tmp_path}/e/documents.parquet")
    assert media.op2_media_columns(spark, f"{tmp_path}/e").count() == 0


# 3


def test_simhash_votes_by_hand(spark):
    d = keyed(docs(spark, ["One two three two", "", "solo", "x " * 9000]))
    t = simhash.terms(d, ["key"], "text")
    got = {r["key"]: r["fp"] for r in simhash.fingerprint(t, ["key"]).collect()}
    for key in got:
        rows = [(r["hash"], r["weight"]) for r in t.filter(F.col("key") == key).collect() if r["hash"] is not None]
        want = 0
        for b in range(64):
            if sum(w if h >> b & 1 else -w for h, w in rows) > 0:
                want |= 1 << b
        assert got[key] & 2**64 - 1 == want
    assert got[1] == 0


def test_votes_of_one_long_word_stay_within_a_long(spark):
    """4096 equal terms of weight 8 would bring the highest lane to 2^63."""
    d = keyed(docs(spark, [f"{w}longword " * 5000 for w in "abcdefgh"]))
    t = simhash.terms(d, ["key"], "text")
    want = {r["key"]: r["h"] for r in t.filter("piece = 0").groupBy("key").agg(F.mode("hash").alias("h")).collect()}
    assert any(h < 0 for h in want.values())
    assert {r["key"]: r["fp"] for r in simhash.fingerprint(t, ["key"]).collect()} == want


def test_texts_are_dealt_once(spark):
    d = keyed(docs(spark, ["one two", "three", "four"] * 5))
    with simhash.dealt_once(spark):
        plan = simhash.with_edited(d)._jdf.queryExecution().executedPlan().toString()
    assert not [x for x in plan.splitlines() if "hashpartitioning(key" in x and "dup" in x.split("hashpartitioning(")[1].split(")")[0]]


def test_edited_text_and_odd_rows(spark, tmp_path):
    d = docs(spark, ["abcdefgh", "XYZ", "é漢🙂w" * 3, ""], start=5)
    got = {r["key"]: r["edited"] for r in simhash.with_edited(keyed(d)).collect()}
    assert got == {5: "abcdefXY", 6: "XYZ", 7: "é漢🙂w" * 2 + "é", 8: ""}
    odd(spark).write.parquet(f"{tmp_path}/documents.parquet")
    rows = {r["doc_id"]: r for r in simhash.op3_simhash(spark, str(tmp_path)).collect()}
    assert set(rows) == {None, 1, 2, 3, 4, 5} and rows[2]["fingerprint"] == rows[3]["fingerprint"] == "0" * 16
    assert simhash.op3_simhash(spark, str(tmp_path)).count() == 7
    empty(spark).write.parquet(f"{tmp_path}/e/documents.parquet")
    assert simhash.op3_simhash(spark, f"{tmp_path}/e").count() == 0


def test_rows_that_share_an_id_all_stay(spark):
    """Against the contract by plain Python: order by id, then by a hash of the text; the next row's text patches this one's."""
    rng = random.Random(4)
    rows = [(rng.choice([None, 1, 2, 3, 9, 40]), rng.choice(["", "one two", "a b c d e f g h", "é漢🙂 end", "one two", "xyz " * rng.randint(1, 9)])) for _ in range(30)]
    d = spark.createDataFrame(rows, "doc_id long, text string").withColumn("dup", F.lit("clash"))
    order = sorted(rows, key=lambda r: (-(2**63) if r[0] is None else r[0], hashlib.md5(r[1].encode()).hexdigest()))
    want = Counter()
    for (i, t), (_, after) in zip(order, [*order[1:], order[0]]):
        cut = len(t) // 4
        want[i, len(t), t[: len(t) - cut] + after[:cut]] += 1
    got = Counter((None if r["key"] == -(2**63) else r["key"], r["n_chars"], r["edited"]) for r in simhash.with_edited(keyed(d)).collect())
    assert got == want


def test_hamming_search_is_exact(spark):
    rng = random.Random(2)
    base = [rng.getrandbits(64) for _ in range(20)]
    fps = sorted({b ^ sum(1 << i for i in rng.sample(range(64), rng.randint(0, 5))) for b in base for _ in range(15)})
    sign = lambda x: x - (1 << 64) if x >> 63 else x
    df = spark.createDataFrame([(sign(f), 1) for f in fps], "fp long, n long")
    for radius, blocks in ((3, 6), (2, 4), (0, 1)):
        got = Counter((r["query_fp"], r["fp"]) for r in simhash.within_radius(df, df.select("fp"), radius, blocks).collect())
        want = Counter((sign(a), sign(b)) for a in fps for b in fps if (a ^ b).bit_count() <= radius)
        assert got == want


# 4


def test_toxicity(spark):
    rng = random.Random(4)
    word = lambda: "".join(rng.choice("abcdefg") for _ in range(5))
    texts, y = [], []
    for i in range(600):
        bad = i % 4 == 0
        t = [word() for _ in range(30)] + (["scum"] * bad) + (["idiot"] * (bad and i % 8 == 0))
        rng.shuffle(t)
        texts.append(" ".join(t))
        y.append(int(bad))
    d = docs(spark, texts)
    labels = spark.createDataFrame([(i, 1, t) for i, t in enumerate(y) if i % 2 == 0] + [(None, 1, 1), (0, 1, None), (99_999, 1, 1)], "doc_id long, quality int, toxic int")
    model = toxicity.train(d, labels)
    assert (np.diff(model.theta) > 0).all()
    got = {r["doc_id"]: r for r in toxicity.score(d.withColumn("toxic", F.lit("clash")), model).collect()}
    assert sum(got[i]["toxic"] == y[i] for i in got) >= 595
    assert all(math.isclose(r["p_grade_0"] + r["p_grade_1"] + r["p_grade_2"], 1) for r in got.values())
    assert toxicity.score(odd(spark), model).count() == 7
    none = toxicity.train(d, labels.filter("toxic = 0"))
    assert {r["toxic"] for r in toxicity.score(d, none).collect()} == {0}
    assert toxicity.score(empty(spark), toxicity.train(empty(spark), labels)).count() == 0


def test_ordinal_fit_recovers_order():
    rng = np.random.default_rng(3)
    rows = [list(np.flatnonzero(rng.random(3) < 0.5)) for _ in range(800)]
    y = np.array([min(2, len(r)) for r in rows])
    w, theta = toxicity.fit_ordinal(rows, y, 3)
    assert (w > 0).all() and theta[0] < theta[1]


# 5


def test_language_model(spark, tmp_path):
    rng = random.Random(5)
    langs = [["the", "cat", "sat", "down.", "and"], ["le", "chat", "est", "là.", "et"]]
    texts = [" ".join(rng.choice(langs[i % 2]) for _ in range(40)) + f" Rare{i}" for i in range(300)] + ["", None]
    d = docs(spark, texts)
    d.write.parquet(f"{tmp_path}/documents.parquet")
    rows = {r["doc_id"]: r for r in maxent_lm.op5_maxent_lm(spark, str(tmp_path)).collect()}
    cut = lambda t: (t or "").encode().lower().split() + [b"\n"]
    held = {i for i in range(len(texts)) if zlib.crc32(str(i).encode()) % 10 == 0}
    c = Counter(w for i, t in enumerate(texts) if i not in held for w in cut(t))
    n, v = sum(c.values()), len(c)
    for i, t in enumerate(texts):
        r, ws = rows[i], cut(t)
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (i in held, len(ws), sum(c[w] > 0 for w in ws), n)
        assert math.isclose(r["base_score"], sum(math.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in ws), rel_tol=1e-9)
    gain = [rows[i]["score"] - rows[i]["base_score"] for i in held]
    assert sum(gain) > 0
    odd(spark).write.parquet(f"{tmp_path}/o/documents.parquet")
    assert maxent_lm.op5_maxent_lm(spark, f"{tmp_path}/o").count() == 7
    empty(spark).write.parquet(f"{tmp_path}/e/documents.parquet")
    assert maxent_lm.op5_maxent_lm(spark, f"{tmp_path}/e").count() == 0


def plain_log10(w, units):
    """log10 probability of a text's units, token by token, from the definition of the model."""
    out = []
    rows = lambda kind, a, b, low, n: int(maxent_lm._hash(kind, np.array([a]), np.array([b]), low, n)[0])
    for i, u in enumerate(units):
        one, two = units[i - 1] if i else maxent_lm.UNITS, units[i - 2] if i > 1 else maxent_lm.UNITS
        cls, slot = int(maxent_lm._CLASS_OF[u]), int(maxent_lm._SLOT_OF[u])
        a = [0, rows(1, one, 0, 1, maxent_lm.CLASS_ROWS), rows(2, one, two, 1, maxent_lm.CLASS_ROWS), rows(3, two, 0, 1, maxent_lm.CLASS_ROWS)]
        b = [cls, rows(5, one, cls, maxent_lm.CLASSES, maxent_lm.WORD_ROWS), rows(6, two, cls, maxent_lm.CLASSES, maxent_lm.WORD_ROWS)]
        p = 1.0
        for table, at, pick in ((w.to_class, a, cls), (w.to_slot, b, slot)):
            z = [math.exp(sum(float(table[r, j]) for r in at)) for j in range(table.shape[1])]
            p *= z[pick] / sum(z)
        out.append(math.log10(p))
    return out


def test_scores_against_a_plain_loop(spark):
    """The whole score of documents: units by a plain softmax, rarer words by their share of their shape."""
    rng = random.Random(6)
    texts = [" ".join(rng.choice(["the", "cat", "sat.", "on", "mat", f"Rare{rng.randint(0, 60)},"]) for _ in range(rng.randint(0, 30))) for _ in range(60)] + ["", None, "unseen words here!"]
    d = maxent_lm.with_split(docs(spark, texts))
    learn = d.filter(~F.col("held_out"))
    counts = maxent_lm.word_counts(learn)
    n = {r["word"].encode(): r["n"] for r in counts.collect()}
    for head in (maxent_lm.HEAD, 8):
        vocab = maxent_lm.vocabulary(counts, head)
        assert len(vocab.words) <= head and all(n[a] > n[b] for a in vocab.words for b in n if b not in vocab.words)
        shared = spark.sparkContext.broadcast(vocab)
        w = maxent_lm.Weights.start(vocab)
        noise = np.random.default_rng(3)
        w.to_class += noise.normal(size=w.to_class.shape).astype(np.float32)
        w.to_slot += noise.normal(size=w.to_slot.shape).astype(np.float32)
        got = {r["doc_id"]: r["score"] for r in maxent_lm.score(d, counts, vocab, shared, w).collect()}
        units = vocab.words[: maxent_lm.UNITS - maxent_lm.SHAPES]
        rest = [x for x in n if x not in units]
        for i, t in enumerate(texts):
            ws = (t or "").encode().lower().split() + [b""]
            us = [units.index(x) if x in units else maxent_lm.UNITS - maxent_lm.SHAPES + maxent_lm.shape(x) for x in ws]
            want = sum(plain_log10(w, us))
            for x in ws:
                if x not in units:
                    mine = [y for y in rest if maxent_lm.shape(y) == maxent_lm.shape(x)]
                    want += math.log10((n.get(x, 0) + 0.1) / (sum(n[y] for y in mine) + 0.1 * (len(mine) + 1)))
            assert math.isclose(got[i], want, rel_tol=1e-4, abs_tol=1e-4), (head, i)


def test_model_sums_to_one():
    words = [b"", *[f"w{i}".encode() for i in range(50)]]
    vocab = maxent_lm.Vocabulary(words, np.arange(51, 0, -1.0), 1326, 51, np.zeros(16), np.zeros(16))
    w = maxent_lm.Weights.start(vocab)
    rng = np.random.default_rng(0)
    w.to_class += rng.normal(size=w.to_class.shape).astype(np.float32)
    w.to_slot += rng.normal(size=w.to_slot.shape).astype(np.float32)
    total = sum(10 ** maxent_lm.log10_prob(w, np.array([7, 3, u]), np.array([0]))[2] for u in range(maxent_lm.UNITS))
    assert math.isclose(total, 1, rel_tol=1e-4)


@pytest.mark.parametrize("word", ["the", "end.", "a,", "naïve!", "漢字", "longword", "x)"])
def test_shape_in_both_forms(spark, word):
    df = spark.createDataFrame([(word,)], "w string")
    assert df.select(maxent_lm.shape_sql("w")).first()[0] == maxent_lm.shape(word.encode())


# 6


def test_warc_round_trip(spark):
    big, other = "<p>" + "x" * 2000, "y" * 1500
    rows = [(1, "u1", big), (2, "u2", big), (9, "u9", big), (9, "u9b", big), (3, "u3", "small"), (4, None, "small"), (5, "u5", None), (6, "u6", other), (None, "n", big), (7, "u7\r\nInjected: 1", "é\r\n\r\n漢")]
    p = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("digest", F.lit("clash"))
    root = scratch(spark, "warc")
    m = warc.write_archives(warc.resolve(p), root)
    from crowding.llm.common import settle

    m = settle(m, "m")
    out = warc.read_archives(m, root).collect()
    got = Counter((r["page_id"], r["record_type"], r["refers_to"], r["payload_bytes"], r["payload_digest"]) for r in out)
    want = Counter()
    for i, _, h in rows:
        b = (h or "").encode()
        rev = h == big and i in (1, 2)
        want[(i, "revisit" if rev else "response", 9 if rev else None, len(b), hashlib.sha1(b).hexdigest())] += 1
    assert got == want
    assert {r["page_id"]: r["payload"] for r in out}[7] == bytearray("é\r\n\r\n漢".encode())
    none = warc.write_archives(warc.resolve(p.filter("false")), root)
    assert none.count() == 0 and warc.read_archives(none, root).count() == 0


# 7


def brute_components(texts, width, num, den):
    def sh(t):
        w = (t or "").encode().lower().split()
        return {tuple(w[i : i + width]) for i in range(len(w) - width + 1)} if len(w) >= width else {tuple(w)} if w else set()

    s = [sh(t) for t in texts]
    up = list(range(len(s)))

    def find(i):
        return i if up[i] == i else find(up[i])

    for i in range(len(s)):
        for j in range(i):
            c = len(s[i] & s[j])
            if s[i] and s[j] and den * c >= num * (len(s[i]) + len(s[j]) - c):
                a, b = sorted((find(i), find(j)))
                up[b] = a
    return {i: (len(s[i]), find(i)) for i in range(len(s))}


def near_texts(seed, n=60):
    rng = random.Random(seed)
    vocab = [f"w{i}" for i in range(30)]
    texts = []
    for _ in range(n // 6):
        base = [rng.choice(vocab) for _ in range(rng.choice([1, 2, 4, 12, 25, 60, 200]))]
        for _ in range(6):
            t = list(base)
            for _ in range(rng.randint(0, max(1, len(t) // 25))):
                t[rng.randrange(len(t))] = rng.choice(vocab)
            texts.append(" ".join(t).title() if rng.random() < 0.3 else "  ".join(t))
    return texts + ["", None, " \n", "one", "ONE", "a b", "A  b"]


@pytest.mark.parametrize("width,num,den,weight", [(3, 90, 100, 1_000_000), (5, 80, 100, 1_000_000), (2, 60, 100, 200), (3, 90, 100, 150)])
def test_jaccard_components_exact(spark, monkeypatch, width, num, den, weight):
    monkeypatch.setattr(jaccard_join, "WEIGHT", weight)
    texts = near_texts(width * weight)
    got = jaccard_join.join_components(keyed(docs(spark, texts)), width, num, den).collect()
    assert {r["key"]: (r["n_shingles"], r["component"]) for r in got} == brute_components(texts, width, num, den)


def test_signatures_meet_every_link():
    rng = random.Random(8)
    for num, den in ((90, 100), (80, 100), (50, 100)):
        limit = jaccard_join.Threshold(num, den)
        for _ in range(150):
            a = {rng.getrandbits(64) for _ in range(rng.choice([3, 20, 150, 800, 1600]))}
            b = set(a)
            for x in rng.sample(sorted(a), rng.randint(0, max(1, len(a) // 6))):
                b.discard(x)
                if rng.random() < 0.6:
                    b.add(rng.getrandbits(64))
            if b and a != b and limit.links(len(a), len(b), len(a & b)):
                sa, sb = (np.array(sorted(x), np.uint64) for x in (a, b))
                rows = jaccard_join.signatures([sa, sb], limit)
                assert len(jaccard_join.shared(rows)) >= 2
                sk = [jaccard_join.sketch(x) for x in (sa, sb)]
                assert jaccard_join.near_pairs(np.array([len(sa), len(sb)]), sk, limit).shape == (1, 2)


def test_candidates_of_a_task_are_a_forest(spark):
    """30 near copies met under 40 signatures of random members: fewer rows than nodes in a task, and all stay connected."""
    rng = random.Random(3)
    limit = jaccard_join.Threshold(80, 100)
    sk = jaccard_join.sketch(np.arange(50, dtype=np.uint64) << np.uint64(58))
    nodes = spark.createDataFrame([(i, 50, sk) for i in range(30)], "node long, n long, sketch binary")
    groups = spark.createDataFrame([(4 * s, i) for s in range(40) for i in ([0, 1 + s % 29] if s < 29 else rng.sample(range(30), 12))], "sign long, node long")
    got = [tuple(r) for r in jaccard_join.candidate_edges(groups, nodes, limit).collect()]
    forest = jaccard_join.Forest(30)
    for a, b in got:
        forest.join(a, b)
    tasks = groups.select(F.pmod("sign", F.lit(jaccard_join.partitions(spark))).alias("t"), "node").groupBy("t").agg(F.count_distinct("node").alias("n")).collect()
    assert forest.trees == 1 and len(got) <= sum(r["n"] - 1 for r in tasks)


def test_candidates_do_not_grow_with_signatures(spark, monkeypatch):
    """One group of near copies met under ever more signatures: each task tells once how it is connected, however many batches it takes."""
    monkeypatch.setattr(jaccard_join, "COMPARED", 50)
    rng = random.Random(4)
    limit = jaccard_join.Threshold(80, 100)
    sk = jaccard_join.sketch(np.arange(50, dtype=np.uint64) << np.uint64(58))
    nodes = spark.createDataFrame([(i, 50, sk) for i in range(60)] + [(60, 50, jaccard_join.sketch(np.arange(50, dtype=np.uint64)))], "node long, n long, sketch binary")
    groups = spark.createDataFrame([(s, i) for s in range(600) for i in rng.sample(range(60), 2 + s % 90 // 2)] + [(600, 0), (600, 60)], "sign long, node long")
    got = [tuple(r) for r in jaccard_join.candidate_edges(groups, nodes, limit).collect()]
    forest = jaccard_join.Forest(61)
    for a, b in got:
        forest.join(a, b)
    assert forest.trees == 2 and forest.find(60) == 60 and len(got) <= 59 * jaccard_join.partitions(spark)
    assert jaccard_join.candidate_edges(groups.limit(0), nodes, limit).count() == 0


def test_near_pairs_connect_what_pairs_would():
    rng = random.Random(12)
    limit = jaccard_join.Threshold(80, 100)
    for _ in range(30):
        base = [frozenset(rng.sample(range(10**9), rng.randint(5, 60))) for _ in range(3)]
        sets = []
        for _ in range(40):
            x = set(rng.choice(base))
            for y in rng.sample(sorted(x), rng.randint(0, 3)):
                x.remove(y)
            sets.append(np.array(sorted(x | {rng.randrange(10**9) for _ in range(rng.randint(0, 2))}), np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        sets = [np.sort(x) for x in sets]
        n, sk = np.array([len(x) for x in sets]), [jaccard_join.sketch(x) for x in sets]
        wide = jaccard_join.stacked(sk, min(map(len, sk)))
        all_, got = jaccard_join.Forest(len(sets)), jaccard_join.Forest(len(sets))
        for i in range(len(sets)):
            for j in range(i):
                small, large = sorted((int(n[i]), int(n[j])))
                if large <= small * 100 // 80 and np.abs(wide[i] - wide[j]).sum() <= (small + large) * 20 // 180:
                    all_.join(i, j)
        for i, j in jaccard_join.near_pairs(n, sk, limit).tolist():
            got.join(i, j)
        assert [all_.find(i) for i in range(len(sets))] == [got.find(i) for i in range(len(sets))]


def test_t_occurrence_against_counting():
    rng = random.Random(9)
    for _ in range(300):
        lists = [np.array(sorted(rng.sample(range(60), rng.randint(0, 40))), np.int64) for _ in range(rng.randint(1, 12))]
        t = rng.randint(1, len(lists))
        want = sorted((i, n) for i, n in Counter(i for x in lists for i in x.tolist()).items() if n >= t)
        assert sorted(jaccard_join.t_occurrence(lists, t)) == want


def test_components_of_large_stars(spark):
    edges = [(0, i) for i in range(1, 700)] + [(1000, i) for i in range(1001, 1400)] + [(1399, 1400), (5000, 5001)]
    got = {r["node"]: r["root"] for r in jaccard_join.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**dict.fromkeys(range(700), 0), **dict.fromkeys(range(1000, 1401), 1000), 5000: 5000, 5001: 5000}


def test_components_on_chains(spark):
    pairs = [(i, i + 1) for i in range(40)] + [(100, 101), (103, 101), (7, 7)]
    got = {r["node"]: r["root"] for r in jaccard_join.components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 101: 100, 103: 100}
    assert jaccard_join.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_keep_one_row(spark):
    out = jaccard_join.keep_one(odd(spark))
    assert Counter(r["doc_id"] for r in out.collect()) == {1: 1, None: 1, 2: 1, 3: 1, 4: 1, 5: 1} and out.columns == odd(spark).columns
    long = " ".join(f"w{i}" for i in range(100))
    assert [r["doc_id"] for r in jaccard_join.keep_one(docs(spark, [long, long + " x", "other text here"])).orderBy("doc_id").collect()] == [0, 2]
    assert jaccard_join.keep_one(empty(spark)).count() == 0


# 8


def test_token_files_read_in_small_pieces(spark, monkeypatch):
    """Offsets, counts and checksums do not depend on shards or on how many documents are read at a time."""
    texts = ["one two three", "", None, "word " * 500, *[f"text number {i}" for i in range(40)]]
    want = None
    for shards, n_docs, n_ids in ((1, 2048, 1 << 22), (7, 3, 1 << 22), (5, 2048, 10)):
        monkeypatch.setattr(elias_fano, "READ_DOCS", n_docs)
        monkeypatch.setattr(elias_fano, "READ_IDS", n_ids)
        root = scratch(spark, "tokens")
        m = elias_fano.write_token_files(docs(spark, texts, start=-5), WORD, root, shards=shards)
        got = sorted(map(tuple, elias_fano.read_shards(spark, m, root).collect()))
        assert want is None or got == want
        want = got
    assert [r[0] for r in want] == list(range(-5, len(texts) - 5)) and want[1][2] == 1


def test_elias_fano_sequences():
    rng = np.random.default_rng(6)
    for v in (np.zeros(1000), np.arange(700), np.sort(rng.integers(0, 2**50, 2000)), np.sort(rng.integers(0, 30, 2000)), np.array([5]), np.array([], dtype=int), np.array([0, 2**62])):
        v = v.astype(np.uint64)
        f = elias_fano.EliasFano.frombytes(elias_fano.EliasFano.encode(v).tobytes())
        assert (f.values() == v).all() and [f.select(i) for i in range(len(v))] == v.tolist()
    with pytest.raises(ValueError):
        elias_fano.EliasFano.encode(np.array([3, 1]))
    dense = elias_fano.EliasFano.encode(np.arange(0, 10**6, 100))
    assert len(dense.tobytes()) < 8 * 10**4 * 0.3


def test_token_files(spark):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(WORD)
    root = scratch(spark, "tok")
    d = odd(spark)
    m = elias_fano.write_token_files(d, WORD, root, shards=3)
    got = sorted(map(tuple, elias_fano.read_shards(spark, m, root).collect()), key=lambda r: r[1])
    at, want = 0, []
    for r in sorted(d.collect(), key=lambda r: (-1 if r["doc_id"] is None else r["doc_id"])):
        ids = tok.encode(r["text"] or "", add_special_tokens=False).ids + [1]
        want.append((r["doc_id"], at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        at += len(ids)
    assert got == want
    s = elias_fano.ShardFile(f"{root}/{m.orderBy('shard').first()['path']}")
    assert s.key(len(s) - 1) >= s.key(0) and s.ids(0)[-1] == 1
    m = elias_fano.write_token_files(empty(spark), WORD, root)
    assert elias_fano.read_shards(spark, m, root).count() == 0


# 9


def test_poisson_mix(spark):
    d = docs(spark, [f"t{i}" for i in range(4000)]).withColumn("copy", F.lit("clash"))
    out = poisson_mix.mix(d, {"s0": 3.0, "s1": 1.0}, rows=4000)
    n = Counter(r["source"] for r in out.collect())
    assert abs(n["s0"] - 3000) < 250 and abs(n["s1"] - 1000) < 150
    reps = Counter(r["doc_id"] for r in out.filter("source = 's0'").collect())
    share = [sum(1 for i in range(0, 4000, 2) if reps[i] == k) / 2000 for k in range(4)]
    assert all(abs(s - math.exp(-1.5) * 1.5**k / math.factorial(k)) < 0.04 for k, s in enumerate(share))
    assert sorted(map(tuple, out.collect())) == sorted(map(tuple, poisson_mix.mix(d, {"s0": 3.0, "s1": 1.0}, rows=4000).collect()))
    keys = [r["shuffle_key"] for r in out.collect()]
    assert keys == sorted(keys)
    assert poisson_mix.mix(empty(spark)).count() == 0 and poisson_mix.mix(odd(spark)).columns[:4] == ["doc_id", "text", "lang", "source"]
    assert poisson_mix.mix(d, {"s0": 0.0}).count() == 0
    with pytest.raises(ValueError):
        poisson_mix.mix(d, {"s0": -1.0})


def plain_mix(rows, rate, seed):
    """Copies of each id, by walking the distribution of each piece."""
    out = {}
    for i, src in rows:
        pieces = max(1, math.ceil(rate[src] / poisson_mix.PIECE))
        lam, total = rate[src] / pieces, 0
        for j in range(pieces):
            u = int(hashlib.md5(f"{seed}:{'null' if i is None else i}{f':p{j}' if j else ''}".encode()).hexdigest()[:8], 16)
            p = c = math.exp(-lam)
            k = 0
            while math.floor(c * 2**32) <= u and k < lam + 12 * math.sqrt(lam) + 24:
                k += 1
                p *= lam / k
                c += p
            total += k
        out[i] = total
    return out


def test_rates_without_limit(spark):
    d = docs(spark, [f"t{i}" for i in range(40)]).withColumn("mix_src", F.lit("clash")).withColumn("Mix_Cuts", F.lit(1))
    one = spark.createDataFrame([(99, "alone", "en", "single", 5), (None, "no source", None, None, 1)], DOCS).withColumn("mix_src", F.lit("x")).withColumn("Mix_Cuts", F.lit(2))
    both = d.unionByName(one)
    weights = {"s0": 1.0, "s1": 0.0, "single": 100.0, None: 0.5}
    out = poisson_mix.mix(both, weights, rows=3000)
    got = Counter(r["doc_id"] for r in out.collect())
    rate = {s: 3000 * w / 101.5 / n for (s, w), n in zip(weights.items(), (20, 20, 1, 1))}
    want = plain_mix([(r["doc_id"], r["source"]) for r in both.collect()], rate, 20)
    assert got == Counter({k: v for k, v in want.items() if v}) and abs(got[99] - rate["single"]) < 300
    assert out.columns == ["doc_id", "text", "lang", "source", "n_chars", "mix_src", "Mix_Cuts", "n_copies", "copy", "shuffle_key"]
    many = spark.range(600_000).select(F.col("id").alias("doc_id"), F.lit("x").alias("text"), F.lit("en").alias("lang"), F.when(F.col("id") == 7, "rare").otherwise("big").alias("source"), F.lit(1).alias("n_chars"))
    n = {r["source"]: r["count"] for r in poisson_mix.mix(many).groupBy("source").count().collect()}
    assert 600 < n["rare"] < 960 and abs(n["big"] - 599_226) < 4000


def test_poisson_sql_with_large_rates(spark, tmp_path):
    import duckdb

    rows = [(i, f"t{i}", "en", "a" if i else "b", 2) for i in range(20_000)] + [(None, None, None, None, None)]
    d = spark.createDataFrame(rows, DOCS)
    got = sorted((r["doc_id"] or -1, r["copy"], r["n_copies"], r["shuffle_key"]) for r in poisson_mix.mix(d).collect())
    d.coalesce(1).write.parquet(f"{tmp_path}/documents.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    names = [c[0] for c in con.execute(f"DESCRIBE {poisson_mix.SQL}").fetchall()]
    want = sorted((r["doc_id"] or -1, r["copy"], r["n_copies"], r["shuffle_key"]) for r in (dict(zip(names, x)) for x in con.execute(poisson_mix.SQL).fetchall()))
    assert got == want and sum(g[0] == -1 for g in got) > 64


def test_poisson_salted_join_is_the_same(spark, monkeypatch):
    d = docs(spark, [f"t{i}" for i in range(300)])
    want = sorted(map(tuple, poisson_mix.mix(d).collect()))
    monkeypatch.setattr(poisson_mix, "BROADCAST_CUTS", 0)
    assert sorted(map(tuple, poisson_mix.mix(d).collect())) == want


# 10


def naive_bpe(word, ranks):
    parts = [bytes([b]) for b in word]
    while len(parts) > 1:
        k, i = min((ranks.get((a, b), 10**9), i) for i, (a, b) in enumerate(zip(parts, parts[1:])))
        if k == 10**9:
            break
        a, b = parts[i], parts[i + 1]
        out, j = [], 0
        while j < len(parts):
            if j + 1 < len(parts) and parts[j] == a and parts[j + 1] == b:
                out.append(a + b)
                j += 2
            else:
                out.append(parts[j])
                j += 1
        parts = out
    return parts


def test_automaton_on_random_merges():
    """Against merging by rank, also with merges that can never be applied and several to one token."""
    rng = random.Random(10)
    dead = twice = refused = 0
    for _ in range(150):
        vocab = {bytes([c]): i for i, c in enumerate(b"abc")}
        merges = []
        while len(merges) < 14:
            a, b = rng.choice(list(vocab)), rng.choice(list(vocab))
            if rng.random() < 0.15 and len(ab := rng.choice(list(vocab))) > 2:
                at = rng.randint(1, len(ab) - 1)
                a, b = ab[:at], ab[at:]
            if (a, b) not in merges and a in vocab and b in vocab:
                merges.append((a, b))
                vocab.setdefault(a + b, len(vocab))
        ranks = {m: i for i, m in enumerate(merges)}
        try:
            auto = bpe_automaton.Automaton(vocab, merges)
        except ValueError:
            assert len({a + b for a, b in merges}) < len(merges)
            refused += 1
            continue
        dead += len(auto.live) < len(vocab)
        twice += len({a + b for a, b in merges}) < len(merges)
        for _ in range(60):
            w = bytes(rng.choice(b"abc") for _ in range(rng.randint(1, 14)))
            assert [auto.label[i] for i in auto.encode(w)] == naive_bpe(w, ranks)
            assert auto.decode(list(auto.encode(w))) == w
    assert dead > 20 and twice > 20 and refused < 60


def test_automaton_accepts_what_merging_leaves():
    """Every token sequence up to three arcs: accepted if and only if merging its text gives it back."""
    from itertools import product

    merges = [(b"a", b"b"), (b"b", b"c"), (b"a", b"bc"), (b"ab", b"ab"), (b"c", b"c"), (b"ab", b"c"), (b"a", b"a")]
    vocab = {bytes([c]): i for i, c in enumerate(b"abc")}
    for a, b in merges:
        vocab.setdefault(a + b, len(vocab))
    auto, ranks = bpe_automaton.Automaton(vocab, merges), {m: i for i, m in enumerate(merges)}
    assert auto.encode(b"abc") == (vocab[b"abc"],) and auto.states <= 1 + len(auto.live)
    for n in (1, 2, 3):
        for seq in product(vocab.values(), repeat=n):
            state = 0
            for x in seq:
                state = auto.step(state, x) if state >= 0 else -1
            text = b"".join(auto.label[x] for x in seq)
            assert (state >= 0) == (naive_bpe(text, ranks) == [auto.label[x] for x in seq])
    short = bpe_automaton.Automaton({b"a": 0, b"b": 1, b"c": 2, b"ab": 3, b"bc": 4, b"abc": 5}, merges[:3])
    assert short.encode(b"abc") == (3, 2) and b"abc" not in short.live
    with pytest.raises(ValueError):
        bpe_automaton.Automaton({b"a": 0, b"b": 1, b"ab": 2, b"abb": 3}, [(b"ab", b"b"), (b"a", b"b")])
    with pytest.raises(ValueError):
        short.encode(b"abx")


def test_bounded_cache():
    from crowding.llm.common import Bounded

    c = Bounded(1000)
    for i in range(100):
        c.keep(i, str(i), 50)
        assert c.find(0) == "0"  # found again and again, it stays
        assert len(c.young) + len(c.old) <= 22
    c.forget()
    assert c.find(99) is None


def test_byte_bpe_is_the_librarys(spark):
    from tokenizers import Tokenizer

    tok, bpe = Tokenizer.from_file(BYTE), bpe_automaton.ByteBpe.of(BYTE)
    rng = random.Random(11)
    pool = [*"ab 's't1٣é́ \n\t\r\x0b\x0c\x1c\x1f\x85\xa0 　漢🙂,.!'ſK", "<|endoftext|>", "  ", "'re", "\n\n", "the", "ing"]
    texts = ["".join(rng.choice(pool) for _ in range(rng.randint(0, 25))) for _ in range(1500)] + ["a" * 20_000, " " * 5000, "", "<|endoftext|>" * 3]
    for t in texts:
        ids = tok.encode(t, add_special_tokens=False).ids
        assert bpe.encode(t) == ids and bpe.decode(ids) == tok.decode(ids, skip_special_tokens=False)
    word = elias_fano.WordEncoder.of(WORD)
    ref = Tokenizer.from_file(WORD)
    for t in texts:
        assert np.frombuffer(word.encode([t.encode()])[0], word.dtype).tolist() == ref.encode(t, add_special_tokens=False).ids


def test_bpe_columns(spark):
    out = bpe_automaton.decode_column(bpe_automaton.encode_column(odd(spark), BYTE), BYTE)
    assert all(r["decoded"] == (r["text"] or "") for r in out.collect())
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(BYTE)
    rows = [(i, t) for i, t in enumerate(["", " ", "Plain text, with marks!", "é漢🙂" * 3000, "x" * 70_000, "a b " * 40_000, "<|endoftext|> twice <|endoftext|>"])] + [(None, "no id"), (3, None), (3, "again")]
    want = Counter()
    for i, t in rows:
        ids = tok.encode(t or "", add_special_tokens=False).ids
        sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
        want[i, len(ids), sha(",".join(map(str, ids))), sha(tok.decode(ids, skip_special_tokens=False))] += 1
    got = bpe_automaton.digests(spark.createDataFrame(rows, "doc_id long, text string").withColumn("ids", F.lit("clash")), BYTE)
    assert Counter(map(tuple, got.collect())) == want
    assert bpe_automaton.digests(odd(spark), BYTE).count() == 7 and bpe_automaton.digests(empty(spark), BYTE).count() == 0
