"""The pipeline's stages against their plain meaning on the smallest tables."""

from pyspark.sql import functions as F

import corpus_pipeline as cp
from crowding.llm import queries

SF = "/root/testdata/sf0.001"


def brute_keep(ids, texts):
    """The smallest id of each group under 5-word shingles and Jaccard 0.8, and all texts without words."""
    sets = []
    for t in texts:
        w = (t or "").encode().lower().split()
        sets.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set())
    up = list(range(len(ids)))

    def find(i):
        return i if up[i] == i else find(up[i])

    for i in range(len(ids)):
        for j in range(i):
            c = len(sets[i] & sets[j])
            if c and 100 * c >= 80 * (len(sets[i]) + len(sets[j]) - c):
                a, b = sorted((find(i), find(j)))
                up[b] = a
    return [ids[i] for i in range(len(ids)) if find(i) == i]


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    clean = cp.drop_toxic(spark, docs, SF)
    labels = {r["doc_id"]: r["toxic"] for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    left = {r["doc_id"]: r["text"] for r in clean.collect()}
    assert clean.columns == docs.columns
    kept = [i in left for i, t in labels.items() if not t]
    assert sum(kept) >= 0.97 * len(kept)
    one = cp.drop_near_copies(spark, clean, SF)
    ids = sorted(left)
    assert sorted(r["doc_id"] for r in one.collect()) == brute_keep(ids, [left[i] for i in ids])
    mixed = cp.mix_sources(spark, one, SF)
    assert mixed.columns == docs.columns and {r["doc_id"] for r in mixed.collect()} <= set(ids)
    out = cp.encode(spark, mixed, SF).collect()
    assert len(out) == mixed.count() and all(r["n_tokens"] == len(r["ids"]) for r in out)


def test_chain_on_odd_rows(spark, tmp_path):
    """All stages over nulls, empty, long and repeated rows and columns with clashing names, against plain Python."""
    from tokenizers import Tokenizer

    import public_tokenizers

    long = " ".join(f"word{i}" for i in range(60_000))
    rows = [(i, f"clean text number {i} about plain things of the day and more words {i * 7}", "en", f"s{i % 2}", 1) for i in range(40)]
    rows += [(40, rows[3][1], "en", "s0", 1), (3, rows[3][1], "en", "s1", 1), (41, None, None, None, None), (42, "", "en", "s0", 0), (None, "no id but some words to read here", "fr", None, 1), (43, long, "en", "s1", 1), (44, long + " end", "en", "s1", 1)]
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    spark.createDataFrame(rows, schema).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([], "doc_id long, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    for name in ("p_grade_0", "key", "mix_src", "ids_", "n", "dd__k2"):
        docs = docs.withColumn(name, F.lit("clash"))
    clean = cp.drop_toxic(spark, docs, str(tmp_path))
    assert clean.count() == len(rows)  # nothing is known of toxic texts
    one = cp.drop_near_copies(spark, docs.drop("p_grade_0"), str(tmp_path))
    left = sorted((-1 if r["doc_id"] is None else r["doc_id"]) for r in one.collect())
    assert left == sorted([*range(40), 41, 42, -1, 43])
    mixed = cp.mix_sources(spark, one, str(tmp_path))
    assert mixed.columns == one.columns and {r["doc_id"] for r in mixed.collect()} <= {r["doc_id"] for r in one.collect()}
    tok = Tokenizer.from_file(str(public_tokenizers.path("byte_bpe_50k.json")))
    text = {r["doc_id"]: r["text"] for r in one.collect()}
    for r in cp.encode(spark, mixed, str(tmp_path)).collect():
        assert r["ids"] == tok.encode(text[r["doc_id"]] or "", add_special_tokens=False).ids and r["n_tokens"] == len(r["ids"])
    none = docs.filter("false")
    for _, stage in cp.STAGES:
        none = stage(spark, none, str(tmp_path))
        assert none.count() == 0


def test_names():
    names = list(queries.queries())
    assert sorted(int(n[2:].split("_")[0]) for n in names) == list(range(1, 11))
    assert [n for n, _ in cp.STAGES] == ["toxicity", "near_copies", "mixing", "bpe"]
