"""Mixing sources to target weights by Poisson replication, in DataFrame functions alone.

Each row draws a count from a Poisson distribution whose mean is its source's repetition rate (target share
of the mixture times rows wanted, over rows there). The draw inverts the distribution at a number in
[0, 2^32) hashed from seed and doc_id, so it needs no state, is the same on every retry and for every copy
of a row. A rate above PIECE is the sum of equal smaller ones, each drawn by a hash of its own, as sums of
independent Poisson counts are Poisson; so no rate is too large. The count explodes the row; sorting by a
second hash shuffles the result globally.

Edge cases: a null source is a source of its own; null ids draw as the text 'null'; repeated rows draw
alike; a source without weight or with weight 0 gets rate 0 and no rows; an empty table stays empty; texts
are carried whole, also null, empty and very long ones; other columns are carried along whatever they are
called, except that copy, n_copies and shuffle_key are replaced.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from crowding.llm.common import settle, table, unused

#: Numbers of all sources' distributions up to which they are broadcast (8 bytes each); beyond it the join is dealt by source and salt.
BROADCAST_CUTS = 1_000_000
SALTS = 64
#: Largest rate drawn at once.
PIECE = 64


def rates(docs: DataFrame, weights: dict[str | None, float] | None = None, rows: int | None = None) -> DataFrame:
    """(src, rate): weights are shares up to a factor (default: square root of a source's rows); rows is the
    size of the mixture (default: rows of the input)."""
    n = docs.groupBy(F.col("source").alias("src")).agg(F.count(F.lit(1)).alias("n"))
    if weights is None:
        n = n.withColumn("w", F.sqrt(F.col("n").cast("double")))
    else:
        if any(not v >= 0 or v == float("inf") for v in weights.values()):
            raise ValueError("weights must be finite and not negative")
        given = docs.sparkSession.createDataFrame([(k, float(v)) for k, v in weights.items()], "s string, w double")
        n = n.join(F.broadcast(given), F.col("src").eqNullSafe(F.col("s")), "left").drop("s").fillna({"w": 0.0})
    sum_w, sum_n = n.agg(F.sum("w"), F.sum("n")).first()
    wanted = float((sum_n or 0) if rows is None else rows)
    share = F.lit(wanted) * F.col("w") / F.lit(sum_w) / F.col("n") if sum_w else F.lit(0.0)
    return n.select("src", share.alias("rate"))


def cut_points(rate: DataFrame) -> DataFrame:
    """(src, pieces, cuts): into how many equal pieces the rate is cut, and of a piece floor(2^32 * P(count <= k))
    for k = 0, 1, ... until the distribution is exhausted."""
    pieces = F.greatest(F.lit(1), F.ceil(F.col("rate") / PIECE)).cast("int")
    one = rate.filter("rate > 0").select("src", pieces.alias("pieces"), (F.col("rate") / pieces).alias("rate"))
    top = F.ceil(F.col("rate") + 12 * F.sqrt("rate") + 24).cast("int")
    cdf = F.aggregate(
        F.sequence(F.lit(1), top),
        F.struct(F.exp(-F.col("rate")).alias("p"), F.array(F.exp(-F.col("rate"))).alias("c")),
        lambda a, k: F.struct((a["p"] * F.col("rate") / k).alias("p"), F.concat(a["c"], F.array(F.element_at(a["c"], -1) + a["p"] * F.col("rate") / k)).alias("c")),
        lambda a: a["c"],
    )
    return one.select("src", "pieces", F.transform(cdf, lambda c: F.floor(c * 4294967296.0)).alias("cuts"))


def draw(seed: int, *parts: "F.Column") -> "F.Column":
    """A number in [0, 2^32) from the hash of the seed and the parts."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), *[F.coalesce(p.cast("string"), F.lit("null")) for p in parts])), 1, 8), 16, 10).cast("long")


def mix(docs: DataFrame, weights: dict[str | None, float] | None = None, rows: int | None = None, seed: int = 20) -> DataFrame:
    """Rows of docs, each as often as drawn, with copy (1..n_copies), n_copies and shuffle_key, in the order of that key."""
    docs = docs.drop("copy", "n_copies", "shuffle_key")
    cuts = settle(cut_points(rates(docs, weights, rows)), "mix-rates")
    total = cuts.agg(F.coalesce(F.sum(F.size("cuts")), F.lit(0))).first()[0]
    src, pieces, cut, salt, at = (unused(docs, f"mix_{c}") for c in ("src", "pieces", "cuts", "salt", "at"))
    known = cuts.withColumnsRenamed({"src": src, "pieces": pieces, "cuts": cut})
    if total <= BROADCAST_CUTS:
        joined = docs.join(F.broadcast(known), F.col("source").eqNullSafe(F.col(src)))
    else:
        many = known.withColumn(salt, F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        salted = docs.withColumn(at, F.pmod(F.xxhash64(F.col("doc_id")), F.lit(SALTS)).cast("int"))
        joined = salted.join(many, F.col("source").eqNullSafe(F.col(src)) & (F.col(at) == F.col(salt))).drop(at, salt)

    def drawn(*parts: "F.Column") -> "F.Column":
        # in an array, lest the number is hashed again for every cut
        once = F.transform(F.array(draw(seed, F.col("doc_id"), *parts)), lambda u: F.size(F.filter(F.col(cut), lambda c: c <= u)))
        return F.get(once, F.lit(0)).cast("long")

    more = F.aggregate(F.sequence(F.lit(1), F.greatest(F.lit(1), F.col(pieces) - 1)), F.lit(0).cast("long"), lambda a, j: a + drawn(F.concat(F.lit("p"), j.cast("string"))))
    out = joined.withColumn("n_copies", drawn() + F.when(F.col(pieces) > 1, more).otherwise(F.lit(0)))
    out = out.filter("n_copies > 0").drop(src, pieces, cut)
    out = out.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("n_copies"))))
    return out.withColumn("shuffle_key", F.md5(F.concat_ws(":", F.lit(str(seed)), F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.col("copy").cast("string")))).orderBy("shuffle_key")


def op9_poisson_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole documents, mixed to the square root of their source's size, in shuffled order."""
    return mix(table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source", "n_chars"))


SQL = r"""
WITH n AS (SELECT source AS src, count(*) AS n FROM documents GROUP BY 1),
w AS (SELECT src, (SELECT sum(n) FROM n) * sqrt(n) / (SELECT sum(sqrt(n)) FROM n) / n AS rate FROM n),
r AS (SELECT src, pieces, rate / pieces AS rate FROM (SELECT src, rate, greatest(1, CAST(ceil(rate / 64) AS BIGINT)) AS pieces FROM w)),
k AS (SELECT src, rate, unnest(range(0, CAST(ceil(rate + 12 * sqrt(rate) + 24) AS BIGINT) + 1)) AS k FROM r),
p AS (SELECT src, k, exp(k * ln(rate) - lgamma(k + 1) - rate) AS p FROM k),
c AS (SELECT src, CAST(floor(sum(p) OVER (PARTITION BY src ORDER BY k) * 4294967296.0) AS BIGINT) AS cut FROM p),
d AS (SELECT documents.*, unnest(range(0, pieces)) AS piece, CAST(doc_id AS VARCHAR) AS id FROM documents JOIN r ON source IS NOT DISTINCT FROM src),
u AS (SELECT *, CAST('0x' || substr(md5('20:' || coalesce(id, 'null') || CASE WHEN piece = 0 THEN '' ELSE ':p' || piece END), 1, 8) AS BIGINT) AS u FROM d),
e AS (SELECT u.doc_id, any_value(text) AS text, any_value(lang) AS lang, any_value(source) AS source,
             any_value(n_chars) AS n_chars, count(*) AS n_copies
      FROM u JOIN c ON u.source IS NOT DISTINCT FROM c.src AND c.cut <= u.u GROUP BY u.doc_id),
x AS (SELECT *, unnest(range(1, n_copies + 1)) AS copy FROM e)
SELECT doc_id, text, lang, source, n_chars, n_copies, copy, md5('20:' || coalesce(CAST(doc_id AS VARCHAR), 'null') || ':' || copy) AS shuffle_key FROM x
"""
