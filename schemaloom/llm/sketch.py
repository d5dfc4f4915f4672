"""Document fingerprints: threshold-scaled sketches of word shingles, in DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from schemaloom.llm.shared import ascii_lower, documents

SHINGLE_WORDS = 5
#: Share of the hash range that a sketch keeps.
FRACTION = 0.25
NO_ID = -(1 << 63)  # stands for a null doc_id, which comes first
MOST_BUCKETS = 8192


def let(value: Column, then) -> Column:
    """then(value), with the value computed once: what a lambda names again and again is else computed each time."""
    return F.get(F.transform(F.array(value), then), 0)


def shingle_hashes(text: Column, words_each: int = SHINGLE_WORDS) -> Column:
    """A 32-bit hash of each run of words_each words; of the whole where there are fewer. Words are what stands between
    ASCII white space, with A-Z lowered."""
    words = F.filter(F.split(ascii_lower(F.coalesce(text, F.lit(""))), "[ \t-\r]+"), lambda x: x != "")

    def runs(hashed: Column) -> Column:
        first = F.sequence(F.lit(1), F.greatest(F.size(hashed) - (words_each - 1), F.lit(1)))
        return F.transform(first, lambda k: F.shiftrightunsigned(F.xxhash64(F.slice(hashed, k, words_each)), 32))

    return let(F.transform(words, lambda x: F.xxhash64(x)), runs)


def below(hashes: Column, fraction: float) -> Column:
    """Sorted distinct hashes below the fraction of their range; the smallest one where none is."""

    def choose(every: Column) -> Column:
        some = F.filter(every, lambda x: x < int(fraction * (1 << 32)))
        return let(some, lambda x: F.when(F.size(x) > 0, F.sort_array(F.array_distinct(x))).otherwise(F.array(F.array_min(every))))

    return let(hashes, choose)


def sketch(text: Column, words_each: int = SHINGLE_WORDS, fraction: float = FRACTION) -> Column:
    return below(shingle_hashes(text, words_each), fraction)


def merged(a: Column, b: Column, fraction: float = FRACTION) -> Column:
    """The sketch of both texts' shingles together, from their sketches."""
    return below(F.array_union(a, b), fraction)


def resemblance(a: Column, b: Column) -> Column:
    """Estimated share of common shingles in all shingles of both."""
    return let(F.size(F.array_intersect(a, b)), lambda both: both / (F.size(a) + F.size(b) - both))


def containment(a: Column, b: Column) -> Column:
    """Estimated share of a's shingles that b has too, however unequal the two."""
    return F.size(F.array_intersect(a, b)) / F.size(a)


def as_text(a: Column) -> Column:
    """Eight hexadecimal digits a hash."""
    return F.array_join(F.transform(a, lambda x: F.lower(F.lpad(F.hex(x), 8, "0"))), "")


def bucket_bounds(docs: DataFrame, key: Column, buckets: int) -> list[int]:
    """Smallest keys of buckets of about equal size, at most `buckets` of them; each is a key of the table."""
    shares = [k / buckets for k in range(1, buckets)]
    row = docs.agg(F.min(key).alias("least"), F.percentile_approx(key, shares, 10 * buckets).alias("cuts") if shares else F.array().alias("cuts")).first()
    return [] if row.least is None else sorted({row.least, *(row.cuts or ())})


def with_next(docs: DataFrame, order: Column, carried: dict[str, Column], per_row: dict[str, Column] | None = None) -> DataFrame:
    """docs with, for each column of carried, its value in the next row by `order` (64-bit integers); after the last
    comes the first. Ties stand by the carried values' hash.

    Rows meet once, in buckets of neighbouring keys; each bucket's first row also goes, as a guest, to the end of the
    bucket before, so no task needs all rows. per_row: columns computed after that exchange and before the look ahead.
    """
    buckets = min(MOST_BUCKETS, 4 * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    bounds = bucket_bounds(docs, order, buckets)
    n = max(1, len(bounds))
    steps = [1 << k for k in reversed(range(n.bit_length()))]
    cuts = F.array(*map(F.lit, bounds)) if bounds else F.array(F.lit(NO_ID))
    rank = F.aggregate(F.array(*map(F.lit, steps)), F.lit(0), lambda at, s: F.when(F.coalesce(F.get(cuts, at + s - 1) <= F.col("_key"), F.lit(False)), at + s).otherwise(at))
    placed = docs.withColumn("_key", order).withColumn("_bucket", rank - 1)
    leads = F.get(cuts, F.col("_bucket")) == F.col("_key")
    guest = F.when(F.col("_bucket") == 0, F.lit(n - 1)).otherwise(F.col("_bucket") - 1)
    seat = lambda bucket, turn: F.struct(bucket.cast("int").alias("at"), F.lit(turn).alias("turn"))  # noqa: E731  turn 1: after the bucket's own
    seats = F.when(leads, F.array(seat(F.col("_bucket"), 0), seat(guest, 1))).otherwise(F.array(seat(F.col("_bucket"), 0)))
    spread = placed.withColumn("_seat", F.explode(seats)).withColumn("_bucket", F.col("_seat.at")).withColumn("_turn", F.col("_seat.turn")).drop("_seat")
    spread = spread.withColumn("_tie", F.xxhash64(*docs.columns))
    met = spread.repartition("_bucket").sortWithinPartitions("_bucket", "_turn", "_key", "_tie")
    for name, value in (per_row or {}).items():
        met = met.withColumn(name, value)
    ahead = Window.partitionBy("_bucket").orderBy("_turn", "_key", "_tie")
    for name, value in carried.items():
        met = met.withColumn(name, F.lead(value).over(ahead))
    return met.where(F.col("_turn") == 0).drop("_key", "_bucket", "_turn", "_tie")


def edited_fingerprints(docs: DataFrame, id_col: str = "doc_id", text: str = "text", words_each: int = SHINGLE_WORDS, fraction: float = FRACTION) -> DataFrame:
    """For each row: id, n_chars, edited (its text with the last quarter replaced by the start of the next), sketch,
    edited_sketch, next_sketch.

    Null texts are empty; a null id comes first; rows that repeat an id follow one another, by their texts' hash; one
    row alone is its own next. Texts without words have the sketch of the empty text. Other columns are left out.
    """
    rows = docs.select(F.col(id_col).cast("long").alias(id_col), F.coalesce(F.col(text), F.lit("")).alias(text))
    found = with_next(rows, F.coalesce(F.col(id_col), F.lit(NO_ID)), {"_next": F.col(text), "next_sketch": F.col("sketch")}, {"sketch": sketch(F.col(text), words_each, fraction)})
    n = F.length(text)
    tail = F.floor(n / 4).cast("int")
    edited = F.concat(F.substring(F.col(text), F.lit(1), n - tail), F.substring(F.col("_next"), F.lit(1), tail))
    found = found.select(id_col, n.cast("long").alias("n_chars"), edited.alias("edited"), "sketch", "next_sketch")
    return found.withColumn("edited_sketch", sketch(F.col("edited"), words_each, fraction))


def op10_scaled_sketch(spark, sf_dir: str) -> DataFrame:
    found = edited_fingerprints(documents(spark, sf_dir))
    return found.select(
        "doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), as_text(F.col("sketch")).alias("fingerprint"), as_text(F.col("edited_sketch")).alias("edited_fingerprint"),
        resemblance(F.col("sketch"), F.col("edited_sketch")).alias("near_edited"), resemblance(F.col("sketch"), F.col("next_sketch")).alias("near_next"),
    )
