"""Order MinHash fingerprints in DataFrame functions alone (operator 1).

A text's k-mers are its runs of five words, numbered by occurrence so that repeats count. One hash
of each numbered k-mer both deals it to a bucket and ranks it there (one-permutation hashing). A
bucket selects its two least k-mers, puts them back in text order, and hashes the pair: the
signature feels which k-mers there are and how they are ordered, as an edit distance does. All of
it stays inside a row; only the look at the next document moves texts.

Arrays of packed longs stand in for structs: a sort key in the upper 40 bits and the place in the
text in the lower 24, so one primitive sort orders them.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pushwave.plans.durable import cut

K, BUCKET_BITS, PICK = 5, 6, 2
BUCKETS = 2**BUCKET_BITS
PLACE_BITS = 24
_PLACE = (1 << PLACE_BITS) - 1
_KEY = ~_PLACE
#: Documents in one group of neighbouring ids when looking for the next document; quantiles of the ids
#: between which groups are cut by width (a power of two).
GROUP, QUANTILES = 256, 1024


def _let(value: Column, body) -> Column:
    """body of a value that is computed once: the optimizer would copy an expression into lambdas."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _words(text: Column) -> Column:
    """Hashes of the words between blanks, A-Z lower-cased with all other letters."""
    plain = F.translate(F.lower(text), "\t\n\x0b\x0c\r", "     ")
    return F.transform(F.filter(F.split(plain, " "), lambda w: w != ""), lambda w: F.xxhash64(w))


def _kmers(words: Column) -> Column:
    """Hash of each k-mer with its place; fewer than K words are one k-mer, none give none."""
    packed = F.transform(
        F.sequence(F.lit(0), F.size(words) - K),
        lambda i: F.xxhash64(*(F.get(words, i + j) for j in range(K))).bitwiseAND(F.lit(_KEY)).bitwiseOR(F.least(i, F.lit(_PLACE)).cast("long")),
    )
    short = F.array(F.xxhash64(F.array_join(F.transform(words, lambda w: w.cast("string")), " ")).bitwiseAND(F.lit(_KEY)))
    return F.when(F.size(words) >= K, packed).when(F.size(words) > 0, short).otherwise(F.array().cast("array<long>"))


def _runs(items: Column, key) -> Column:
    """(begin, end) of the runs of equal keys in a sorted array that is not empty."""
    begins = F.filter(F.sequence(F.lit(0), F.size(items) - 1), lambda i: (i == 0) | (key(F.get(items, i)) != key(F.get(items, i - 1))))
    return _let(begins, lambda b: F.transform(b, lambda x, j: F.struct(x.alias("b"), F.coalesce(F.get(b, j + 1), F.size(items)).alias("e"))))


def _numbered(kmers: Column) -> Column:
    """Each k-mer's occurrence hash with its place; kmers sorted by hash and place."""
    of = lambda run: F.transform(
        F.sequence(run["b"], run["e"] - 1),
        lambda i: F.xxhash64(F.get(kmers, i).bitwiseAND(F.lit(_KEY)), i - run["b"]).bitwiseAND(F.lit(_KEY)).bitwiseOR(F.get(kmers, i).bitwiseAND(F.lit(_PLACE))),
    )
    repeated = F.flatten(F.transform(_runs(kmers, lambda x: F.shiftright(x, PLACE_BITS)), of))
    once = F.transform(kmers, lambda x: F.xxhash64(x.bitwiseAND(F.lit(_KEY)), F.lit(0)).bitwiseAND(F.lit(_KEY)).bitwiseOR(x.bitwiseAND(F.lit(_PLACE))))
    keys = F.transform(kmers, lambda x: F.shiftright(x, PLACE_BITS))
    return F.when(F.size(F.array_distinct(keys)) == F.size(kmers), once).otherwise(repeated)


def _signature(numbered: Column) -> Column:
    """map of bucket to tuple hash; numbered sorted by hash, so buckets follow each other."""
    bucket = lambda x: F.shiftright(x, 64 - BUCKET_BITS)
    place = lambda x: x.bitwiseAND(F.lit(_PLACE))

    def pick(run: Column) -> Column:
        a, b = F.get(numbered, run["b"]), F.get(numbered, run["b"] + 1)
        alone = run["e"] - run["b"] < PICK
        first, second = F.when(place(a) <= place(b), a).otherwise(b), F.when(place(a) <= place(b), b).otherwise(a)
        pair = F.xxhash64(F.shiftright(first, PLACE_BITS), F.shiftright(second, PLACE_BITS))
        return F.struct((bucket(a) + BUCKETS // 2).cast("int").alias("k"), F.when(alone, F.xxhash64(F.shiftright(a, PLACE_BITS))).otherwise(pair).alias("v"))

    return F.map_from_entries(F.transform(_runs(numbered, bucket), pick))


def _by_bucket(signature: Column) -> Column:
    """The tuple hash of every bucket as a 32-bit number, null for an empty bucket."""
    return _let(signature, lambda m: F.transform(F.sequence(F.lit(0), F.lit(BUCKETS - 1)), lambda i: F.element_at(m, i).bitwiseAND(F.lit(0x7FFFFFFF)).cast("int")))


def fingerprint(text: Column) -> Column:
    """The fingerprint of a text (null: empty) as an array of BUCKETS numbers."""
    empty = F.array_repeat(F.lit(None).cast("int"), BUCKETS)
    signed = lambda n: F.when(F.size(n) == 0, empty).otherwise(_by_bucket(_signature(n)))
    ranked = lambda k: _let(F.array_sort(F.when(F.size(k) > 0, _numbered(k)).otherwise(k)), signed)
    return _let(_words(F.coalesce(text, F.lit(""))), lambda w: _let(F.array_sort(_kmers(w)), ranked))


def digits(numbers: Column) -> Column:
    """A fingerprint in print: eight hex digits a bucket, eight dots for an empty one."""
    return F.array_join(F.transform(numbers, lambda x: F.coalesce(F.lower(F.lpad(F.hex(x), 8, "0")), F.lit("........"))), "")


def likeness(a: Column, b: Column) -> Column:
    """Share of equal buckets among those filled in either, to the power 1/2: a pair of k-mers must
    match for a bucket to match, so the root is on the scale of single k-mers. Two texts without
    words are alike."""
    equal = F.size(F.filter(F.zip_with(a, b, lambda x, y: x == y), lambda z: z))
    neither = F.size(F.filter(F.zip_with(a, b, lambda x, y: x.isNull() & y.isNull()), lambda z: z))
    return F.when(neither == BUCKETS, F.lit(1.0)).otherwise(F.sqrt(equal / F.greatest(F.lit(1), F.lit(BUCKETS) - neither)))


def _groups(docs: DataFrame) -> Column:
    """A number for each row's group, rising with doc_id; null ids are before all.

    Quantiles of the ids are the borders of equally many rows, wherever the ids lie, so an outlier
    only widens the piece that it is in; a piece is cut further by width, in floating point, which
    keeps the order of ids and holds any difference of two longs.
    """
    steps = [i / QUANTILES for i in range(1, QUANTILES)]
    n, low, high, inner = docs.agg(F.count("doc_id"), F.min("doc_id"), F.max("doc_id"), F.percentile_approx("doc_id", steps, 4 * QUANTILES)).first()
    if not n:
        return F.lit(-1).cast("long")
    borders = sorted({low, *inner})
    value, piece = F.col("doc_id"), F.lit(0)
    known = F.lit(borders).cast("array<long>")

    def ahead(step: int):
        return lambda p: F.when((p + step <= len(borders)) & (F.get(known, p + (step - 1)) <= value), p + step).otherwise(p)

    for bit in reversed(range(QUANTILES.bit_length())):  # borders at or below the id, by bisection
        piece = _let(piece, ahead(1 << bit))
    cuts = -(-n // (QUANTILES * GROUP))
    if cuts == 1:
        number = piece.cast("long")
    else:
        ends = F.lit([float(x) for x in borders[1:]] + [float(high) + 1.0])
        starts = F.lit([float(x) for x in borders])
        part = lambda p: p.cast("long") * cuts + F.least(F.lit(cuts - 1).cast("long"), F.floor((value.cast("double") - F.get(starts, p - 1)) / F.greatest(F.lit(1.0), F.get(ends, p - 1) - F.get(starts, p - 1)) * cuts))
        number = _let(piece, part)
    return F.when(value.isNull(), F.lit(-1).cast("long")).otherwise(number)


def with_next(docs: DataFrame, columns: list[str]) -> DataFrame:
    """docs (doc_id, ...) with the values of columns in the next row by doc_id as next_<column>.

    Ids, any longs, are dealt to groups of neighbours, so only a group is ordered at a time; the last
    row of a group takes the first row of the next group, and the last of all the first of all. Null
    ids come before all others; equal ids follow in order of the columns.
    """
    grouped = docs.withColumn("_g", _groups(docs))
    order = [F.col("doc_id").asc_nulls_first(), *columns]
    inside = Window.partitionBy("_g").orderBy(*order)
    heads = grouped.withColumn("_r", F.row_number().over(inside)).filter("_r = 1").select("_g", *(F.col(c).alias(f"_h_{c}") for c in columns))
    # Groups in a row: ordered inside spans, then over the spans' first groups, which are few.
    ids = grouped.select("_g").distinct().withColumn("_s", F.floor(F.col("_g") / 4096))
    spans = ids.groupBy("_s").agg(F.min("_g").alias("first"))
    after = spans.withColumn("next", F.coalesce(F.lead("first").over(Window.orderBy("_s")), F.min("first").over(Window.orderBy("_s").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))).select("_s", "next")
    follow = ids.withColumn("lead", F.lead("_g").over(Window.partitionBy("_s").orderBy("_g"))).join(after, "_s").select(F.col("_g").alias("_of"), F.coalesce("lead", "next").alias("_g"))
    border = follow.join(heads, "_g").drop("_g").withColumnRenamed("_of", "_g")
    led = grouped.select("*", *(F.lead(c).over(inside).alias(f"_l_{c}") for c in columns), F.lead(F.lit(1)).over(inside).alias("_more"))
    joined = led.join(border, "_g", "left")
    return joined.select(*docs.columns, *(F.when(F.col("_more") == 1, F.col(f"_l_{c}")).otherwise(F.col(f"_h_{c}")).alias(f"next_{c}") for c in columns))


def edit_report(docs: DataFrame) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next.

    The edited text has its last floor(n_chars/4) code points replaced by the first as many (or
    all) of the next document, by doc_id; after the last comes the first. Null texts are empty;
    empty and blank texts have a fingerprint of dots and are alike. A table of one row is its own
    next; an empty table gives an empty table. Repeated rows are documents of their own. Only
    doc_id and text are read. Texts of over 2**24 words keep all k-mers, the places beyond tie.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    paired = with_next(docs.withColumn("id", F.col("doc_id")), ["text", "id"])
    n, quarter = F.char_length("text"), F.floor(F.char_length("text") / 4).cast("int")
    changed = F.concat(F.substring(F.col("text"), F.lit(1), n - quarter), F.substring(F.col("next_text"), F.lit(1), quarter))
    edited = paired.select("doc_id", "text", n.cast("long").alias("n_chars"), F.xxhash64("text").alias("tid"), F.col("next_id"), F.xxhash64("next_text").alias("next_tid"), changed.alias("edited"))
    slim = edited.select("doc_id", "tid", "next_id", "next_tid", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), fingerprint(F.col("text")).alias("own"), fingerprint(F.col("edited")).alias("changed"))
    slim = cut(slim, "order-minhash")
    # The next document's fingerprint, by its id and the hash of its text; repeated rows are one here.
    other = slim.groupBy(F.col("doc_id").alias("next_id"), F.col("tid").alias("next_tid")).agg(F.first("own").alias("following"))
    there = slim.alias("a").join(other.alias("b"), F.col("a.next_id").eqNullSafe(F.col("b.next_id")) & (F.col("a.next_tid") == F.col("b.next_tid")))
    return there.select("doc_id", "n_chars", "edited_sha256", digits(F.col("own")).alias("fingerprint"), digits(F.col("changed")).alias("edited_fingerprint"), likeness(F.col("own"), F.col("changed")).alias("near_edited"), likeness(F.col("own"), F.col("following")).alias("near_next"))
