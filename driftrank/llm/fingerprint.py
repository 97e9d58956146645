"""Document fingerprints by one-permutation MinHash, with DataFrame functions only.

Each text's five-word shingles are hashed once; the top bits of a hash choose one of BINS bins, whose least hash counts.
An empty bin takes the value of the first full bin among TRIES bins drawn by its own hashes, or, if all those are empty,
of the first full one in its own random order of all bins (optimal densification). The BITS low-order bits of each bin are packed as hex; likeness is the share
of equal bins, corrected for chance agreement of BITS bits.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from driftrank.llm import words as W

BINS, BITS, SHINGLE, TRIES = 128, 8, 5, 16
_LOW = (1 << 57) - 1
SPACE = r"[ \t\n\x0b\f\r]+"


def let(value: Column, body) -> Column:
    """Evaluate ``value`` once and bind it in ``body``."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def shingle_hashes(text: Column) -> Column:
    words = F.filter(F.split(F.coalesce(text, F.lit("")), SPACE), lambda w: w != "")
    hashed = F.transform(words, lambda w: F.xxhash64(w))

    def runs(h):
        many = F.transform(F.sequence(F.lit(0), F.size(h) - SHINGLE), lambda i: F.xxhash64(*(F.get(h, i + k) for k in range(SHINGLE))))
        few = F.when(F.size(h) > 0, F.array(F.xxhash64(h))).otherwise(F.array().cast("array<long>"))
        return F.when(F.size(h) >= SHINGLE, many).otherwise(few)

    return let(hashed, runs)


def _probe(b: int, t: int) -> int:
    """The bin that empty bin ``b`` looks at in its t-th try."""
    x = (b * TRIES + t + 1) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF
    x = (x ^ (x >> 29)) * 0xBF58476D1CE4E5B9 & 0xFFFFFFFFFFFFFFFF
    return (x >> 33) % BINS


def fingerprint(text: Column) -> Column:
    """Packed fingerprint, 2 hex digits for each bin; '' for a null text or one without words."""
    ends = F.array(*(F.lit(_signed((b << 57) | _LOW)) for b in range(BINS)))
    bin_of = lambda x: F.shiftrightunsigned(x, 57)
    empty = lambda x: x.bitwiseAND(F.lit(_LOW)) == F.lit(_LOW)

    def first_of_bins(s):
        return F.filter(s, lambda x, i: (i == 0) | (bin_of(x) != bin_of(F.get(s, i - 1))))

    def densified(d):
        tries = [F.array(*(F.lit(_probe(b, t)) for b in range(BINS))) for t in range(TRIES)]

        held = lambda v: F.when(~empty(v), v)

        def fill(x, i):
            tried = (F.get(d, F.get(t, i)) for t in tries)
            full = F.filter(d, lambda v: ~empty(v))
            rest = F.array_min(F.transform(full, lambda v: F.struct(F.xxhash64(i, bin_of(v)).alias("p"), v.alias("v")))).getField("v")
            return F.when(~empty(x), x).otherwise(F.coalesce(*(held(v) for v in tried), rest))

        return F.transform(d, fill)

    def packed(d):
        digits = F.array(*(F.lit(f"{v:0{BITS // 4}x}") for v in range(1 << BITS)))
        return F.array_join(F.transform(d, lambda x: F.get(digits, x.bitwiseAND(F.lit((1 << BITS) - 1)).cast("int"))), "")

    def whole(h):
        mins = let(F.sort_array(F.concat(h, ends)), first_of_bins)
        return F.when(F.size(h) > 0, packed(let(mins, densified))).otherwise(F.lit(""))

    return let(shingle_hashes(text), whole)


def likeness(a: Column, b: Column) -> Column:
    """Estimated Jaccard similarity of two fingerprints, 0 to 1; 1 for two empty ones, 0 if one is empty."""
    w = BITS // 4
    same = F.size(F.filter(F.sequence(F.lit(0), F.lit(BINS - 1)), lambda i: F.substring(a, i * w + 1, F.lit(w)) == F.substring(b, i * w + 1, F.lit(w))))
    chance = 2.0**-BITS
    corrected = F.greatest(F.lit(0.0), (same / BINS - chance) / (1 - chance))
    return F.when(a == b, 1.0).when((a == "") | (b == ""), 0.0).otherwise(corrected)


def fingerprints(frame: DataFrame) -> DataFrame:
    """``frame`` with a fingerprint column; rows and other columns stay as they are."""
    return frame.withColumn("fingerprint", fingerprint(F.col("text")))


RANGE = 50_000  # rows of one range of ids, about


def with_next(frame: DataFrame, pieces: int | None = None) -> DataFrame:
    """(doc_id, text, fingerprint, next_text, next_fingerprint): the next row by descending doc_id (ties by text hash); after the last, the first.

    Rows are dealt into ``pieces`` ranges of doc_id at approximate quantiles (RANGE rows each, at least two a shuffle
    partition and at most 10,000, the exactness of the quantiles); rows without an id are a range of their own. A copy of each range's first row is put at
    the end of the range above, so one exchange and windows inside ranges are enough.
    """
    base = frame.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("th", F.xxhash64("text"))
    pieces = pieces or min(10_000, max(2 * W.partitions(frame.sparkSession), frame.count() // RANGE))
    cuts = base.agg(F.percentile_approx("doc_id", [k / pieces for k in range(1, pieces)] or [0.5], 10000).alias("q")).first()["q"] or []
    cuts = sorted(set(cuts))
    bounds = F.array(*map(F.lit, cuts)) if cuts else F.array().cast("array<long>")
    base = base.withColumn("r", F.when(F.col("doc_id").isNull(), -1).otherwise(F.size(F.filter(bounds, lambda c: c < F.col("doc_id")))))
    # struct maxima of longs: null ids sort lowest, as they do in the window
    tops = base.groupBy("r").agg(F.max(F.struct("doc_id", "th")).alias("k")).collect()  # one row a range
    tops = sorted(((t["r"], t["k"]["doc_id"], t["k"]["th"]) for t in tops), reverse=True)
    if not tops:
        return fingerprints(base.select("doc_id", "text")).selectExpr("*", "text as next_text", "fingerprint as next_fingerprint")
    heads = [(tops[k - 1][0], tops[k][1], tops[k][2]) for k in range(1, len(tops))] + [(tops[-1][0], tops[0][1], tops[0][2])]
    heads = frame.sparkSession.createDataFrame(heads, "r0 int, d long, t long")
    extra = base.drop("r").join(F.broadcast(heads), F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("th") == F.col("t")))
    extra = extra.dropDuplicates(["r0"]).select("doc_id", "text", "th", F.col("r0").alias("r"), F.lit(1).alias("copy"))
    rows = fingerprints(base.select("doc_id", "text", "th", "r", F.lit(0).alias("copy")).union(extra))
    order = Window.partitionBy("r").orderBy("copy", F.col("doc_id").desc_nulls_last(), F.col("th").desc())
    rows = rows.withColumns({f"next_{c}": F.lead(c).over(order) for c in ("text", "fingerprint")})
    return rows.where("copy = 0").select("doc_id", "text", "fingerprint", "next_text", "next_fingerprint")


def op8_fingerprint(spark, sf_dir) -> DataFrame:
    pairs = with_next(W.docs(spark, sf_dir).select("doc_id", "text"))
    n = F.length("text")
    cut = F.floor(n / 3).cast("int")
    pairs = pairs.withColumn("edited", F.concat(F.substring(F.col("text"), F.lit(1), n - cut), F.substring(F.col("next_text"), F.lit(1), cut)))
    pairs = pairs.withColumns({"edited_fingerprint": fingerprint(F.col("edited")), "n_chars": n.cast("long"), "edited_sha256": F.sha2("edited", 256)})
    a = F.col("fingerprint")
    return pairs.select("doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", likeness(a, F.col("edited_fingerprint")).alias("near_edited"), likeness(a, F.col("next_fingerprint")).alias("near_next"))
