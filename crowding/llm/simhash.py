"""SimHash fingerprints and exact Hamming search, in DataFrame functions alone.

Terms are runs of up to three words at every word position, in lower case; a term weighs its first word's
length, 8 at most, and counts as often as it occurs. Each term's 64-bit hash votes with its weight for or
against every bit. Votes are summed as packed counters: 16 longs of four 16-bit lanes, over pieces of at
most 2048 positions, so that no lane can overflow and the highest one stays below the sign of its long (2048 * 8 < 2^15);
then pieces are unpacked and added.

Search cuts fingerprints into blocks; two of them within the radius agree on all but that many blocks, so
one of the permuted tables, keyed by every choice of the other blocks, holds both under the same key. A
pair counts in the first table where it agrees, hence once.

Edge cases: a null text is empty, and an empty text, having no terms, has fingerprint 0; a null doc_id is
one more id, ordered before all others; rows that share a doc_id all stay, each a document, one behind the other in
the order of a hash of their texts; equal texts have equal fingerprints; columns other than those named are ignored. The document after
the last is the first; a single document is its own successor.
"""

from __future__ import annotations

from contextlib import contextmanager
from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from crowding.llm.common import bucket_of, keyed, partitions, range_bounds, settle, table, unkey

RADIUS = 3
BLOCKS = 6
_LANES = 0x0001000100010001
_PIECE = 11  # bits of a position within a piece


def numbered(docs: DataFrame, *cols: str) -> DataFrame:
    """(key, dup, n_chars, *cols): dup tells rows of one id apart, 1 and up in the order of a hash of their texts."""
    w = W.partitionBy("key").orderBy("h")
    rows = docs.select("key", F.md5("text").alias("h"), F.char_length("text").cast("long").alias("n_chars"), *cols)
    return rows.select("key", F.row_number().over(w).alias("dup"), "n_chars", *cols)


def terms(rows: DataFrame, keys: list[str], text: str) -> DataFrame:
    """keys, hash, weight, piece: one row per term occurrence, or one of nulls for a text without words."""
    words = rows.select(*keys, F.regexp_extract_all(F.lower(text), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0)).alias("words"))
    term = F.transform(
        "words",
        lambda w, i: F.struct(
            F.xxhash64(w, F.get("words", i + 1), F.get("words", i + 2)).alias("hash"),
            F.least(F.char_length(w), F.lit(8)).cast("long").alias("weight"),
            F.shiftright(i, _PIECE).alias("piece"),
        ),
    )
    return words.select(*keys, F.inline_outer(term))


def fingerprint(term_rows: DataFrame, keys: list[str]) -> DataFrame:
    """keys, fp: the sign of the weighted vote on each of 64 bits."""
    lanes = [F.sum(F.col("weight") * F.shiftrightunsigned("hash", j).bitwiseAND(F.lit(_LANES))).alias(f"p{j}") for j in range(16)]
    pieces = term_rows.groupBy(*keys, "piece").agg(F.sum("weight").alias("all"), *lanes)
    votes = [F.sum(F.shiftrightunsigned(f"p{i % 16}", 16 * (i // 16)).bitwiseAND(F.lit(0xFFFF))).alias(f"v{i}") for i in range(64)]
    bits = [F.when(F.col(f"v{i}") * 2 > F.col("all"), F.lit((1 << i) - (1 << 64 if i == 63 else 0)).cast("long")).otherwise(F.lit(0).cast("long")) for i in range(64)]
    while len(bits) > 1:
        bits = [a.bitwiseOR(b) for a, b in zip(bits[::2], bits[1::2])]
    return pieces.groupBy(*keys).agg(F.sum("all").alias("all"), *votes).select(*keys, F.coalesce(bits[0], F.lit(0).cast("long")).alias("fp"))


def distance(a: "F.Column", b: "F.Column") -> "F.Column":
    return F.bit_count(a.bitwiseXOR(b))


def hex16(c: str) -> "F.Column":
    return F.lower(F.lpad(F.hex(c), 16, "0"))


def permuted_masks(radius: int, blocks: int) -> list[int]:
    """One mask per table: the blocks two fingerprints within the radius may be asked to share there."""
    if not 0 <= radius < blocks <= 64:
        raise ValueError("the radius must be below the number of blocks")
    cuts = [64 * i // blocks for i in range(blocks + 1)]
    spans = [((1 << b) - 1) ^ ((1 << a) - 1) for a, b in zip(cuts, cuts[1:])]
    return [sum(pick) for pick in combinations(spans, blocks - radius)]


def _signed(mask: int) -> "F.Column":
    return F.lit(mask - (1 << 64) if mask >> 63 else mask).cast("long")


def within_radius(fps: DataFrame, queries: DataFrame, radius: int = RADIUS, blocks: int = BLOCKS) -> DataFrame:
    """(query_fp, fp, n, dist) of all pairs within the radius: fps has distinct fp with n, queries distinct fp.

    Blocks of fingerprints that all agree are met by queries alone, never by each other.
    """
    masks = permuted_masks(radius, blocks)

    def dealt(df: DataFrame, cols: list) -> DataFrame:
        keys = F.array(*[F.struct(F.lit(t).alias("t"), F.col("fp").bitwiseAND(_signed(m)).alias("k")) for t, m in enumerate(masks)])
        return df.select(*cols, F.inline(keys))

    q = dealt(queries.select("fp"), [F.col("fp").alias("query_fp")])
    e = dealt(fps, ["fp", "n"])
    x = F.col("query_fp").bitwiseXOR(F.col("fp"))
    first = F.lit(len(masks))
    for t in reversed(range(len(masks))):
        first = F.when(x.bitwiseAND(_signed(masks[t])) == 0, F.lit(t)).otherwise(first)
    near = e.join(q.hint("merge"), ["t", "k"]).filter((F.bit_count(x) <= radius) & (first == F.col("t")))
    return near.select("query_fp", "fp", "n", F.bit_count(x).alias("dist"))


def successors(rows: DataFrame, parts: int) -> DataFrame:
    """(key, dup, n_chars, next_key, next_dup) in ascending order, the first following the last; (key, dup) are distinct.

    Only the first of every range of keys, a row per range, comes to the driver.
    """
    bounds = range_bounds(rows, "key", min(parts, 4096))
    dealt = rows.withColumn("bucket", bucket_of("key", bounds))
    here = F.struct("key", "dup")
    heads = {r["bucket"]: (r["head"]["key"], r["head"]["dup"]) for r in dealt.groupBy("bucket").agg(F.min(here).alias("head")).collect()}
    if not heads:
        return rows.select("key", "dup", "n_chars", F.col("key").alias("next_key"), F.col("dup").alias("next_dup"))
    order = sorted(heads)
    follow = {b: heads[order[(i + 1) % len(order)]] for i, b in enumerate(order)}
    tail = F.array(*[F.struct(F.lit(k).cast("long").alias("key"), F.lit(d).cast("int").alias("dup")) for k, d in (follow.get(b, heads[order[0]]) for b in range(len(bounds) + 1))])
    after = F.coalesce(F.lead(here).over(W.partitionBy("bucket").orderBy("key", "dup")), F.get(tail, F.col("bucket")))
    return dealt.select("key", "dup", "n_chars", after.alias("after")).select("key", "dup", "n_chars", F.col("after")["key"].alias("next_key"), F.col("after")["dup"].alias("next_dup"))


def with_edited(docs: DataFrame) -> DataFrame:
    """key, dup, next_key, next_dup, text, n_chars, edited: the text whose last quarter of code points is the next text's beginning."""
    ids = ["key", "dup"]
    base = numbered(docs, "text").drop("n_chars")
    follow = successors(numbered(docs), partitions(docs.sparkSession))
    asked = follow.select(F.col("next_key").alias("key"), F.col("next_dup").alias("dup"), F.col("key").alias("asker"), F.col("dup").alias("asker_dup"), F.floor(F.col("n_chars") / 4).cast("int").alias("need"))
    # sides that grow with the documents are never broadcast
    given = base.join(asked.hint("merge"), ids).select(F.col("asker").alias("key"), F.col("asker_dup").alias("dup"), F.substring("text", F.lit(1), F.col("need")).alias("patch"), "need")
    return (
        base.join(given.hint("merge"), ids).join(follow.hint("merge"), ids)
        .select(*ids, "next_key", "next_dup", "text", "n_chars", F.concat(F.substring("text", F.lit(1), (F.col("n_chars") - F.col("need")).cast("int")), F.col("patch")).alias("edited"))
    )


@contextmanager
def dealt_once(spark: SparkSession):
    """Texts dealt by key to be numbered stay where they are to be joined by (key, dup), instead of travelling again."""
    name = "spark.sql.requireAllClusterKeysForCoPartition"
    before = spark.conf.get(name)
    spark.conf.set(name, "false")
    try:
        yield
    finally:
        spark.conf.set(name, before)


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints of every text and its edited text, their likeness, and for every 20th id how many
    documents lie within the radius of it (n_within; null for others)."""
    rows = with_edited(keyed(table(spark, sf_dir, "documents")))
    both = rows.select(
        "key", "dup", "next_key", "next_dup", "n_chars", F.sha2("edited", 256).alias("edited_sha256"),
        F.inline(F.array(F.struct(F.lit(0).alias("edit"), F.col("text").alias("body")), F.struct(F.lit(1).alias("edit"), F.col("edited").alias("body")))),
    )
    keys = ["key", "dup", "next_key", "next_dup", "n_chars", "edited_sha256", "edit"]
    fps = fingerprint(terms(both, keys, "body"), keys)
    pair = fps.groupBy(*keys[:-1]).agg(F.max(F.when(F.col("edit") == 0, F.col("fp"))).alias("fp"), F.max(F.when(F.col("edit") == 1, F.col("fp"))).alias("edited_fp"))
    with dealt_once(spark):
        pair = settle(pair, "fingerprints")
    groups = pair.groupBy("fp").agg(F.count(F.lit(1)).alias("n"))
    asked = pair.filter(F.pmod(F.col("key"), F.lit(20)) == 0).select("fp").distinct()
    found = within_radius(groups, asked).groupBy(F.col("query_fp").alias("fp")).agg(F.sum("n").alias("n_found"))
    after = pair.select(F.col("key").alias("next_key"), F.col("dup").alias("next_dup"), F.col("fp").alias("next_fp"))
    like = lambda a, b: F.lit(1.0) - distance(F.col(a), F.col(b)) / F.lit(64.0)
    return pair.join(after.hint("merge"), ["next_key", "next_dup"]).join(found.hint("merge"), "fp", "left").select(
        unkey().alias("doc_id"), "n_chars", "edited_sha256", hex16("fp").alias("fingerprint"), hex16("edited_fp").alias("edited_fingerprint"),
        like("fp", "edited_fp").alias("near_edited"), like("fp", "next_fp").alias("near_next"),
        F.when(F.pmod(F.col("key"), F.lit(20)) == 0, F.col("n_found")).alias("n_within"),
    )
