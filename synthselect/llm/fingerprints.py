"""Document fingerprints: one-permutation MinHash, in DataFrame functions only.

Every five-word shingle is hashed once; the upper bits name one of 256 bins, which keeps the smallest
rest.  An empty bin tries places drawn by a hash of (bin, round) until one was filled (optimal
densification); after some rounds it takes the first filled bin of its own random order, so it always ends.  The low 8 bits of each bin are stored, and the share of
equal bins is corrected for the matches that low bits have by chance.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

WORDS = 5
BINS = 256
BITS = 8
#: Rounds of densification before the random order decides.
ROUNDS = 8
#: Documents of one range of ids; see next_text.
RANGE_ROWS = 500
MOST_RANGES = 1 << 16


def shingle_hashes(words: Column, n: int = WORDS) -> Column:
    """63-bit hashes of all runs of n of the words' hashes; one of the whole if there are fewer."""
    run = lambda i: F.shiftrightunsigned(F.xxhash64(*[F.get(words, i + k) for k in range(n)]), 1)
    return F.transform(F.sequence(F.lit(0), F.greatest(F.size(words) - n, F.lit(0))), run)


def with_bins(df: DataFrame, text: str, out: str) -> DataFrame:
    """Add `out`: low-order bytes (array<int>) of the densified bins, or null where there is no word.

    The upper bits of a hash are its bin, so in sorted order a bin's smallest hash is the first of its run.
    """
    top = 63 - (BINS.bit_length() - 1)  # hashes have 63 bits
    bin_of = lambda h: F.shiftright(h, top)
    w = F.filter(F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), r"[ \t\n\x0B\f\r]+"), lambda x: x != "")
    df = df.withColumn("_w", F.transform(w, lambda x: F.xxhash64(x)))
    df = df.withColumn("_h", F.when(F.size("_w") > 0, F.sort_array(shingle_hashes(F.col("_w")))))
    df = df.withColumn("_f", F.filter("_h", lambda h, i: (i == 0) | (bin_of(h) != bin_of(F.get(F.col("_h"), i - 1)))))
    df = df.withColumn("_b", F.transform("_f", bin_of))
    df = df.withColumn("_v", F.transform(F.expr(f"sequence(0L, {BINS - 1}L)"), lambda b: F.get(F.col("_f"), F.array_position("_b", b).cast("int") - 1)))
    df = df.withColumn("_v", F.when(F.col("_h").isNotNull(), F.col("_v"))).withColumn("_d", F.col("_v"))
    for t in range(1, ROUNDS + 1):  # an empty bin takes what its next place holds, if that was filled from the start
        df = df.withColumn("_d", F.transform("_d", _borrow(t)))

    def lend(b: Column) -> Column:
        """Where the places of all rounds were empty: the filled bin with the least hash of (this bin, that bin)."""
        j = F.array_min(F.transform("_b", lambda j: F.xxhash64(b.cast("long"), j).bitwiseAND(F.lit(-BINS)).bitwiseOR(j)))
        return F.get(F.col("_v"), j.bitwiseAND(F.lit(BINS - 1).cast("long")).cast("int"))

    rest = F.when(F.exists("_d", lambda v: v.isNull()), F.transform("_d", lambda v, b: F.coalesce(v, lend(b)))).otherwise(F.col("_d"))
    lanes = F.transform(rest, lambda v: v.bitwiseAND(F.lit((1 << BITS) - 1).cast("long")).cast("int"))
    return df.withColumn("_d", F.when(F.col("_h").isNotNull(), F.col("_d"))).withColumn(out, F.when(F.col("_h").isNotNull(), lanes)).drop("_w", "_h", "_f", "_b", "_v", "_d")


def _borrow(t: int):
    return lambda v, b: F.coalesce(v, F.get(F.col("_v"), F.pmod(F.xxhash64(b, F.lit(t)), F.lit(BINS)).cast("int")))


def packed(lanes: Column) -> Column:
    """The bytes of the bins as 512 hex digits; 512 zeros where the text has no word."""
    digits = F.array_join(F.transform(lanes, lambda x: F.lpad(F.hex(x), 2, "0")), "")
    return F.coalesce(F.lower(digits), F.lit("0" * (2 * BINS)))


def likeness(a: Column, b: Column) -> Column:
    """Estimated share of common shingles, 0 to 1: equal lanes less those equal by chance (2^-8).

    Two texts without words are alike (1); one of them with any other is not (0).
    """
    chance = 2.0**-BITS
    same = F.aggregate(F.zip_with(a, b, lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, x: s + x) / BINS
    full = F.greatest(F.lit(0.0), (same - chance) / (1 - chance))
    return F.when(a.isNull() & b.isNull(), 1.0).when(a.isNull() | b.isNull(), 0.0).otherwise(full)


def with_next(df: DataFrame, order: list[str], key: str, carry: list[str]) -> DataFrame:
    """Add next_<c>: c of the next row by (key, *order); the last row gets the first row's.

    Rows are dealt by ranges of `key` whose bounds are values of it; every row at a bound also stands,
    marked, at the end of the range before, so each range finds its successors without a second join.
    The bounds that come to the driver number at most MOST_RANGES.
    """
    n, low = df.agg(F.count(F.lit(1)), F.min(key)).first()
    if not n:
        bounds = []
    else:
        k = int(min(MOST_RANGES, max(1, -(-n // RANGE_ROWS))))
        q = df.agg(F.percentile_approx(key, [i / k for i in range(1, k)], 20 * k)).first()[0] if k > 1 else []
        bounds = sorted({int(b) for b in q or () if b is not None and b > low})
    step = max(1, int(len(bounds) ** 0.5))
    coarse = bounds[::step]
    whole = F.array(*[F.lit(b) for b in bounds]).cast("array<long>") if bounds else F.array().cast("array<long>")
    if bounds:
        below = F.size(F.filter(F.array(*[F.lit(b) for b in coarse]).cast("array<long>"), lambda b: b <= F.col(key)))
        start = F.greatest(F.lit(0), below - 1) * step
        inner = F.size(F.filter(F.slice(whole, start + 1, step), lambda b: b <= F.col(key)))
        df = df.withColumn("_r", F.when(below > 0, start + inner).otherwise(F.lit(0)))
        at_bound = (F.col("_r") > 0) & (F.get(whole, F.col("_r") - 1) == F.col(key))
    else:
        df = df.withColumn("_r", F.lit(0))
        at_bound = F.lit(False)
    last = len(bounds)
    places = F.array(F.struct(F.col("_r").alias("r"), F.lit(0).alias("mark")))
    places = F.when(F.col(key) == F.lit(low), F.array_append(places, F.struct(F.lit(last).alias("r"), F.lit(1).alias("mark")))).when(at_bound, F.array_append(places, F.struct((F.col("_r") - 1).alias("r"), F.lit(1).alias("mark")))).otherwise(places)
    df = df.withColumn("_p", F.explode(places)).withColumns({"_r": F.col("_p.r"), "_mark": F.col("_p.mark")}).drop("_p")
    over = Window.partitionBy("_r").orderBy("_mark", key, *order)
    return df.withColumns({f"next_{c}": F.lead(c).over(over) for c in carry}).filter(F.col("_mark") == 0).drop("_mark", "_r")


def fingerprints(docs: DataFrame) -> DataFrame:
    """Per row: doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next.

    The edited text has its last floor(n_chars / 4) code points replaced by the first as many of the next
    document's text (all, if that is shorter).  Null texts count as empty; a text without words has a
    fingerprint of zeros.  Rows that share a doc_id follow each other by text; a null doc_id comes before
    all others.  A single row is its own next one.  Other columns aren't looked at.
    """
    low = -(1 << 63)
    d = docs.select(F.col("doc_id").cast("long"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    d = with_bins(d, "text", "lanes").withColumn("_k", F.coalesce("doc_id", F.lit(low)))
    d = with_next(d, ["text"], "_k", ["text", "lanes"])
    n = F.length("text")
    cut = F.expr("length(text) div 4").cast("int")
    d = d.withColumn("n_chars", n.cast("long")).withColumn("edited", F.concat(F.substring(F.col("text"), F.lit(1), n - cut), F.substring(F.col("next_text"), F.lit(1), cut)))
    d = with_bins(d.drop("next_text", "text"), "edited", "edited_lanes")
    return d.select(
        "doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), packed(F.col("lanes")).alias("fingerprint"), packed(F.col("edited_lanes")).alias("edited_fingerprint"),
        likeness(F.col("lanes"), F.col("edited_lanes")).alias("near_edited"), likeness(F.col("lanes"), F.col("next_lanes")).alias("near_next"),
    )


def op1_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints(common.read(spark, sf_dir, "documents"))
