"""SimHash near-duplicates by covering locality-sensitive hashing (operator 3).

Every bit position carries a non-zero vector of radius + 1 bits; table v keeps the positions
whose vector has odd parity with v. Two fingerprints that differ in at most radius positions
have, by linear algebra, a non-zero v that is even with all of those positions, so that table
keeps none of them and the pair meets there. Only different fingerprints enter the tables (copies
are folded first). Buckets are range-partitioned by (table, key, fingerprint) and streamed; a
bucket hands on a spanning forest, never its pairs. A bucket that crosses partitions is settled
in a second pass, and one above the size limit by probing: each member looks up the fingerprints
at distance 1 .. radius inside the bucket's free positions with an equi-join, which is exact and
linear in the members.

Near-dedup (keep_one_similar) links texts by their fingerprints first, as operator 3 does, and loses none of
these links. No small radius of the fingerprint reaches all pairs of a stated Jaccard similarity of shingle
sets, so an exact search for these follows among the classes that fingerprints leave: it finds candidates by
prefix filtering, links members of a bucket to one of them first, so that a group is not listed as all its
pairs, and decides each of its links on the whole sets.
"""

from __future__ import annotations

from itertools import combinations, count

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pushwave.llm.common import Batches, fresh, raw, table, tidy
from pushwave.llm.components import components
from pushwave.plans.durable import cut

BITS, SHINGLE, SEED = 64, 3, 42
#: Largest bucket that one task compares by itself.
LIMIT = 4096
#: What keep_one_similar calls near: words of a shingle, and the least Jaccard similarity as a fraction.
NEAR_SHINGLE, NEAR = 5, (4, 5)
#: Documents sampled, about, and shingles kept at most, for the order in which sets are searched.
ORDER_DOCS, ORDER_SHINGLES = 20_000, 50_000
#: Buckets are compared in whole if that takes at most FEW pairs a row, or once a turn of comparing members
#: with one of them leaves more than WORTH of the pairs.
FEW, WORTH = 8, 0.7
#: Bits of a set's parities, a multiple of 64; more bits tell longer sets apart, any number finds the same pairs.
PARITIES = 256


def fingerprint(text: bytes | None) -> int:
    """Bit i is set if more than half of the shingle hashes have it; no words: 0."""
    words = (text or b"").lower().split()
    if not words:
        return 0
    digest = xxhash.xxh64_intdigest
    if len(words) < SHINGLE:
        grams = [b" ".join(words)]
    else:
        grams = map(b" ".join, zip(words, words[1:], words[2:], strict=False))
    hashes = np.fromiter((digest(g, SEED) for g in grams), np.uint64)
    ones = np.zeros(BITS, np.int64)
    for s in range(0, len(hashes), 65536):
        part = hashes[s : s + 65536].view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(part, axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(hashes), bitorder="little").view(np.uint64)[0])


def _signed(x: int) -> int:
    return x - 2**64 if x >= 2**63 else x


def masks(radius: int) -> list[int]:
    """One kept-positions mask for each non-zero v of radius + 1 bits."""
    n = 2 ** (radius + 1)
    vector = [i % (n - 1) + 1 for i in range(BITS)]
    return [sum(1 << i for i in range(BITS) if (vector[i] & v).bit_count() % 2) for v in range(1, n)]


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, tid, fp): the id, the hash of the text, and the fingerprint of each row."""

    def run(batches: Batches) -> Batches:
        schema = pa.schema([("doc_id", pa.int64()), ("tid", pa.int64()), ("fp", pa.int64())])
        for b in batches:
            yield table(schema, b.column("doc_id").to_pylist(), b.column("tid").to_pylist(), [_signed(fingerprint(x)) for x in raw(b, "text")])

    text = F.coalesce("text", F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("tid"), text.alias("text")).mapInArrow(tidy(run), "doc_id long, tid long, fp long")


LINK_SCHEMA = "kind int, t int, a long, b long"
_ARROW = pa.schema([("kind", pa.int32()), ("t", pa.int32()), ("a", pa.int64()), ("b", pa.int64())])
LINK, MEMBER = 0, 1


def _forest(fp: np.ndarray, run: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Links (member, root) that span what is linked inside each run; run ids ascend."""
    n = len(fp)
    label = np.arange(n)
    sizes = np.bincount(run - run[0])
    wide = sizes[run - run[0]] > 64
    pairs = []
    idx = np.flatnonzero(~wide)
    step = 1
    while len(idx):
        idx = idx[idx + step < n]
        idx = idx[run[idx] == run[idx + step]]
        hit = idx[np.bitwise_count(fp[idx] ^ fp[idx + step]) <= radius]
        if len(hit):
            pairs.append(np.stack([hit, hit + step]))
        step += 1
    if pairs:
        a, b = np.concatenate(pairs, axis=1)
        while True:
            low = np.minimum(label[a], label[b])
            before = label.copy()
            np.minimum.at(label, a, low)
            np.minimum.at(label, b, low)
            label = label[label]
            if (label == before).all():
                break
    for r in np.unique(run[wide]):
        left = np.flatnonzero(run == r)
        while len(left):
            root, left = left[0], left[1:]
            front = [root]
            while front and len(left):
                near = np.bitwise_count(fp[left] ^ fp[front.pop()]) <= radius
                got = left[near]
                label[got] = root
                front.extend(got.tolist())
                left = left[~near]
    moved = np.flatnonzero(label != np.arange(n))
    return moved, label[moved]


def _buckets(radius: int, edges: bool):
    """edges: the partition's first and last bucket may go on elsewhere, so they leave as members."""

    def links(t, fp, run):
        m, root = _forest(fp, run, radius)
        if len(m):
            a, b = fp[root].view(np.int64), fp[m].view(np.int64)
            yield table(_ARROW, np.zeros(len(m), np.int32), t[m], a, b)

    def members(t, fp):
        yield table(_ARROW, np.ones(len(t), np.int32), t, fp.view(np.int64), np.zeros(len(t), np.int64))

    def stream(batches: Batches) -> Batches:
        held = None  # rows of the bucket that is going on
        first, over = edges, False
        for batch in batches:
            if not batch.num_rows:
                continue
            t, key, fp = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("t", "key", "fp"))
            fp = fp.view(np.uint64)
            if held is not None:
                t, key, fp = (np.concatenate([h, x]) for h, x in zip(held, (t, key, fp), strict=True))
            new = np.ones(len(t), bool)
            new[1:] = (t[1:] != t[:-1]) | (key[1:] != key[:-1])
            starts = np.flatnonzero(new)
            run = np.cumsum(new) - 1
            last = int(starts[-1])
            if over and len(starts) > 1:  # the rows of the bucket that was over the limit end here
                end = int(starts[1])
                yield from members(t[1:end], fp[1:end])
                t, key, fp, run, starts, last, over, first = t[end:], key[end:], fp[end:], run[end:], starts[1:] - end, last - end, False, False
            elif over:
                yield from members(t[1:], fp[1:])
                held = (t[:1], key[:1], fp[:1])
                continue
            if last and first:
                end = int(starts[1])
                yield from members(t[:end], fp[:end])
                t, key, fp, run, last, first = t[end:], key[end:], fp[end:], run[end:], last - end, False
            if last:
                yield from links(t[:last], fp[:last], run[:last])
            held = (t[last:], key[last:], fp[last:])
            if len(held[0]) > LIMIT:
                yield from members(held[0], held[2])
                held, over = tuple(h[:1] for h in held), True
        if held is not None and not over:
            if edges:
                yield from members(held[0], held[2])
            elif len(held[0]) > 1:
                yield from links(held[0], held[2], np.zeros(len(held[0]), np.int64))

    return stream


def links(different: DataFrame, radius: int = 2) -> DataFrame:
    """(a, b) links whose components are those of all pairs within radius; different: distinct fp."""
    spark = different.sparkSession
    kept = masks(radius)
    entries = F.array(*(F.struct(F.lit(t).alias("t"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("key")) for t, m in enumerate(kept)))
    spread = different.select("fp", F.explode(entries).alias("e")).select("e.t", "e.key", "fp")
    order = ("t", "key", "fp")
    told = cut(spread.repartitionByRange(*order).sortWithinPartitions(*order).mapInArrow(_buckets(radius, True), LINK_SCHEMA), "buckets")
    mask_of = F.element_at(F.array(*(F.lit(_signed(m)) for m in kept)), F.col("t") + 1)
    rest = told.filter(F.col("kind") == MEMBER).select("t", F.col("a").alias("fp")).withColumn("key", F.col("fp").bitwiseAND(mask_of))
    counts = rest.groupBy("t", "key").agg(F.count(F.lit(1)).alias("n"))
    sized = rest.join(counts, ["t", "key"])
    crossing = sized.filter(F.col("n").between(2, LIMIT)).select("t", "key", "fp").repartition("t", "key").sortWithinPartitions(*order)
    second = crossing.mapInArrow(_buckets(radius, False), LINK_SCHEMA)
    wide = sized.filter(F.col("n") > LIMIT).select("t", "fp")
    steps = [(t, _signed(sum(1 << i for i in c))) for t, m in enumerate(kept) for size in range(1, radius + 1) for c in combinations([i for i in range(BITS) if not m >> i & 1], size)]
    probes = spark.createDataFrame(steps, "t int, step long")  # fixed: a few thousand rows
    probed = wide.join(F.broadcast(probes), "t").select("t", F.col("fp").alias("a"), F.col("fp").bitwiseXOR(F.col("step")).alias("fp"))
    third = probed.filter(F.col("a") < F.col("fp")).join(wide, ["t", "fp"]).select("a", F.col("fp").alias("b"))
    return told.filter(F.col("kind") == LINK).select("a", "b").unionByName(second.filter(F.col("kind") == LINK).select("a", "b")).unionByName(third)


def _classes(docs: DataFrame, radius: int) -> tuple[DataFrame, DataFrame]:
    """Fingerprint rows, and (f, root) of the fingerprints that are linked to another one."""
    fps = cut(fingerprints(docs), "fingerprints")
    found = components(links(fps.select("fp").distinct(), radius))
    return fps, cut(found.select(F.col("node").alias("f"), "root"), "components")


def shingle_set(text: bytes | None) -> np.ndarray:
    """Hashes of the different shingles of NEAR_SHINGLE words, ascending; fewer words are one shingle, none give none."""
    words = (text or b"").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    digest = xxhash.xxh64_intdigest
    grams = [words] if len(words) < NEAR_SHINGLE else zip(*(words[i:] for i in range(NEAR_SHINGLE)), strict=False)
    return np.unique(np.fromiter((digest(b" ".join(g), SEED) for g in grams), np.uint64))


def _parities(grams: np.ndarray) -> np.ndarray:
    """PARITIES bits: bit i is odd if an odd number of the hashes is i modulo PARITIES.

    Every shingle that only one of two sets holds changes one bit, so two sets differ in at least as many
    shingles as their parities differ in bits.
    """
    held = np.bincount((grams % np.uint64(PARITIES)).astype(np.int64), minlength=PARITIES)
    return np.packbits((held & 1).astype(np.uint8)).view(np.int64)


def _set_id(grams: np.ndarray) -> int:
    return _signed(xxhash.xxh64_intdigest(grams.tobytes(), SEED))


def _common_shingles(docs: DataFrame) -> np.ndarray:
    """The shingles that repeat most in a sample of about ORDER_DOCS documents, the rarer first.

    They only say which shingles come last in the order; every order finds the same pairs.
    """

    def run(batches: Batches) -> Batches:
        schema = pa.schema([("h", pa.int64())])
        for b in batches:
            for text in raw(b, "text"):
                yield table(schema, shingle_set(text).view(np.int64))

    every = max(1, docs.count() // ORDER_DOCS)
    text = F.coalesce("text", F.lit(""))
    sample = docs.select(text.alias("text")).filter(F.pmod(F.xxhash64("text"), F.lit(every)) == 0)
    counts = sample.mapInArrow(run, "h long").groupBy("h").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= 4)
    got = counts.orderBy(F.desc("n"), "h").limit(ORDER_SHINGLES).select("h").toArrow()  # of a fixed number
    return got.column("h").to_numpy()[::-1].astype(np.int64).view(np.uint64)


def _set_rows(docs: DataFrame) -> DataFrame:
    """(doc_id, tid, fp, mark, n, prefix, odd): fp stands for the set; mark: the fingerprint of the text; prefix: the
    set's first shingles in the common order; odd: its parities.

    Sets of n and m shingles with a Jaccard similarity of NEAR share one of the first n - ceil(NEAR n) + 1
    and m - ceil(NEAR m) + 1 shingles in any order.
    """
    shared = docs.sparkSession.sparkContext.broadcast(_common_shingles(docs))

    def run(batches: Batches) -> Batches:
        schema = pa.schema([("doc_id", pa.int64()), ("tid", pa.int64()), ("fp", pa.int64()), ("mark", pa.int64()), ("n", pa.int32()), ("prefix", pa.list_(pa.int64())), ("odd", pa.list_(pa.int64()))])
        common = shared.value
        rank = np.argsort(common, kind="stable")
        known = common[rank]
        for b in batches:
            rows, size = [], 0
            for doc_id, tid, text in zip(b.column("doc_id").to_pylist(), b.column("tid").to_pylist(), raw(b, "text"), strict=True):
                grams = shingle_set(text)
                n = len(grams)
                first = grams
                if n and len(known):
                    at = np.minimum(np.searchsorted(known, grams), len(known) - 1)
                    first = grams[np.argsort(np.where(known[at] == grams, rank[at], -1), kind="stable")]
                keep = n - -(-NEAR[0] * n // NEAR[1]) + 1 if n else 0
                rows.append((doc_id, tid, _set_id(grams), _signed(fingerprint(text)), n, first[:keep].view(np.int64), _parities(grams)))
                size += keep
                if size > 200_000:
                    yield table(schema, *zip(*rows, strict=True))
                    rows, size = [], 0
            if rows:
                yield table(schema, *zip(*rows, strict=True))

    text = F.coalesce("text", F.lit(""))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("tid"), text.alias("text"))
    return rows.mapInArrow(tidy(run), "doc_id long, tid long, fp long, mark long, n int, prefix array<long>, odd array<long>")


def _whole_sets(docs: DataFrame, asked: DataFrame) -> DataFrame:
    """(fp, grams) of the asked sets, from the texts again; asked: tid of one text of each."""

    def run(batches: Batches) -> Batches:
        schema = pa.schema([("fp", pa.int64()), ("grams", pa.list_(pa.int64()))])
        for b in batches:
            for text in raw(b, "text"):
                grams = shingle_set(text)
                yield table(schema, [_set_id(grams)], [grams.view(np.int64)])

    text = F.coalesce("text", F.lit(""))
    texts = docs.select(F.xxhash64(text).alias("tid"), text.alias("text")).join(asked, "tid", "left_semi").select("text")
    return texts.mapInArrow(tidy(run), "fp long, grams array<long>").groupBy("fp").agg(F.first("grams").alias("grams"))


def _alike(docs: DataFrame, sets: DataFrame, pairs: DataFrame) -> DataFrame:
    """The rows of pairs (a, b) whose whole sets have a Jaccard similarity of NEAR or more."""
    up, down = NEAR
    ends = pairs.select(F.col("a").alias("fp")).unionByName(pairs.select(F.col("b").alias("fp"))).distinct()
    asked = cut(sets.select("fp", "tid").join(ends, "fp", "left_semi").groupBy("fp").agg(F.min("tid").alias("tid")).select("tid"), "asked")
    whole = cut(_whole_sets(docs, asked), "sets")
    left = pairs.join(whole.select(F.col("fp").alias("a"), F.col("grams").alias("ga")), "a")
    both = left.join(whole.select(F.col("fp").alias("b"), F.col("grams").alias("gb")), "b")
    shared = F.size(F.array_intersect("ga", "gb"))
    return both.filter(shared * (up + down) >= (F.size("ga") + F.size("gb")) * up).select("a", "b")


def _prefix_rows(sets: DataFrame) -> DataFrame:
    """(h, fp, n, at, before, lone): the prefix shingles that different sets share.

    at: place in the prefix; before: how many of the places before it are shared by any set, so at most
    that many are common to a pair; lone: shingles of the prefix that no other set has there.
    """
    each = sets.groupBy("fp").agg(F.first("n").alias("n"), F.first("prefix").alias("prefix"))
    entries = cut(each.select("fp", "n", F.size("prefix").alias("kept"), F.posexplode("prefix").alias("at", "h")), "prefixes")
    shared = entries.groupBy("h").agg(F.count(F.lit(1)).alias("k")).filter("k > 1").select("h")
    own = Window.partitionBy("fp")  # rows of one set
    both = entries.join(shared, "h", "left_semi")
    before = F.row_number().over(own.orderBy("at")) - 1
    return cut(both.select("h", "fp", "n", "at", before.alias("before"), (F.col("kept") - F.count(F.lit(1)).over(own)).alias("lone")), "shared")


def _mixed(entries: DataFrame, links: DataFrame | None) -> DataFrame:
    """The entries of buckets that hold more than one class, with root, the class that links make, main, the
    class that most rows of the bucket are in, and size and others, the rows of the bucket and those outside main."""
    if links is None:
        rooted = entries.withColumn("root", F.col("fp"))
    else:
        found = components(links).select(F.col("node").alias("fp"), "root")
        rooted = cut(entries.join(found, "fp", "left").withColumn("root", F.coalesce("root", "fp")), "rooted")
    held = rooted.groupBy("h", "root").agg(F.count(F.lit(1)).alias("k"))
    main = held.groupBy("h").agg(F.max(F.struct("k", "root")).alias("top"), F.sum("k").alias("size"))
    open_ = main.filter(F.col("top.k") < F.col("size")).select("h", F.col("top.root").alias("main"), "size", (F.col("size") - F.col("top.k")).alias("others"))
    return cut(rooted.join(open_, "h"), "mixed")


def _hub_pairs(mixed: DataFrame, turn: int) -> DataFrame:
    """(a, b): in each bucket of more than FEW rows one member with each of the other classes.

    In the first turn it is a member whose prefix is shared most, as that of a text is of which the others are
    edited copies; then any member.
    """
    large = mixed.filter(F.col("size") > FEW)
    order = F.struct(F.col("lone") if turn == 0 else F.lit(0), F.xxhash64("fp", F.lit(turn)), "fp", "n", "root")
    hubs = large.groupBy("h").agg(F.min(order).alias("hub")).select("h", F.col("hub.fp").alias("hub"), F.col("hub.n").alias("hub_n"), F.col("hub.root").alias("hub_root"))
    near = F.least("n", "hub_n") * NEAR[1] >= F.greatest("n", "hub_n") * NEAR[0]
    return large.join(hubs, "h").filter((F.col("root") != F.col("hub_root")) & near).select(F.least("fp", "hub").alias("a"), F.greatest("fp", "hub").alias("b")).distinct()


def _marked_links(sets: DataFrame, radius: int) -> DataFrame:
    """(a, b) links of sets, whose components are those of all texts with fingerprints within radius; sets: fp, mark."""
    both = cut(sets.select("fp", "mark").distinct(), "marks")
    heads = cut(both.groupBy("mark").agg(F.min("fp").alias("head")), "heads")  # one set stands for each fingerprint
    same = both.join(heads, "mark").filter("fp <> head").select(F.col("head").alias("a"), F.col("fp").alias("b"))
    near = links(heads.select(F.col("mark").alias("fp")), radius)
    a, b = (heads.select(F.col("mark").alias(m), F.col("head").alias(h)) for m, h in (("a", "ha"), ("b", "hb")))
    apart = near.join(a, "a").join(b, "b").filter("ha <> hb").select(F.col("ha").alias("a"), F.col("hb").alias("b"))
    return cut(same.unionByName(apart), "marked-links")


def similar_sets(docs: DataFrame, sets: DataFrame, links: DataFrame | None = None) -> DataFrame:
    """(a, b) links whose components are those of links and of all pairs of different sets with a Jaccard similarity
    of NEAR or more; every link that is not of links is such a pair.

    Sets that share a prefix shingle meet in its bucket. First the members of a bucket are compared with
    one of them, so a large group of near copies becomes one class in work linear in its rows. Turns
    end when the pairs that are left are few for the rows, or when a turn links little. Then all pairs
    of different classes are compared: their parities and what they share of their prefixes bound what they can
    have in common (up to the last shared shingle all shared ones are counted, and so are they up to the
    end of the prefix that ends first), and whole sets decide.
    """
    up, down = NEAR
    entries, left = _prefix_rows(sets), None
    for turn in count():
        mixed = _mixed(entries, links)
        rows, pairs = mixed.agg(F.count(F.lit(1)), F.sum(F.col("others").cast("double"))).first()
        if not rows or pairs <= FEW * rows or (left is not None and pairs > left * WORTH):
            break
        left = pairs
        more = _alike(docs, sets, cut(_hub_pairs(mixed, turn), "hubs"))
        links = cut(more if links is None else links.unionByName(more), "near-links")
    odd = sets.groupBy("fp").agg(F.first("odd").alias("odd"))
    words = [F.col("odd")[i].alias(f"odd{i}") for i in range(PARITIES // 64)]
    mixed = mixed.join(odd, "fp").select(*mixed.columns, *words)
    fields = ("fp", "n", "at", "before", "root", *(f"odd{i}" for i in range(PARITIES // 64)))
    a = mixed.filter("root <> main").select("h", *(F.col(c).alias(f"{c}_a") for c in fields))
    b = mixed.select("h", "main", *(F.col(c).alias(f"{c}_b") for c in fields))
    once = (F.col("root_b") == F.col("main")) | (F.col("fp_a") < F.col("fp_b"))
    after = F.least(F.col("n_a") - F.col("at_a"), F.col("n_b") - F.col("at_b")) - 1
    needed = (F.col("n_a") + F.col("n_b")) * up
    able = (F.least("n_a", "n_b") * down >= F.greatest("n_a", "n_b") * up) & ((F.least("before_a", "before_b") + 1 + after) * (up + down) >= needed)
    differ = sum((F.bit_count(F.col(f"odd{i}_a").bitwiseXOR(F.col(f"odd{i}_b"))) for i in range(PARITIES // 64)), F.lit(0))
    close = differ * (up + down) <= (F.col("n_a") + F.col("n_b")) * (down - up)
    met = a.join(b, "h").filter((F.col("root_a") != F.col("root_b")) & once & able & close)
    first = F.col("fp_a") < F.col("fp_b")
    ends = [F.when(first, F.col(f"{c}_{x}")).otherwise(F.col(f"{c}_{y}")).alias(f"{c}_{x}") for c in ("fp", "n", "at") for x, y in ("ab", "ba")]
    sums = met.select(*ends).groupBy("fp_a", "fp_b", "n_a", "n_b").agg(F.count(F.lit(1)).alias("n"), F.max("at_a").alias("at_a"), F.max("at_b").alias("at_b"))
    beyond = F.ceil(F.greatest("n_a", "n_b") * up / down) - 1
    able = ((F.col("n") + after) * (up + down) >= needed) & ((F.col("n") + beyond) * (up + down) >= needed)
    found = _alike(docs, sets, cut(sums.filter(able).select(F.col("fp_a").alias("a"), F.col("fp_b").alias("b")), "pairs"))
    return found if links is None else links.unionByName(found)


def _near_classes(docs: DataFrame, radius: int) -> tuple[DataFrame, DataFrame]:
    """As _classes, of shingle sets: fp stands for the set; links are those of fingerprints and pairs of similarity
    NEAR or more."""
    sets = cut(_set_rows(docs), "shingle-sets")
    found = components(similar_sets(docs, sets, _marked_links(sets, radius)))
    return sets.select("doc_id", "tid", "fp"), cut(found.select(F.col("node").alias("f"), "root"), "components")


#: A fingerprint that more than one row in HOT shares is dealt to SALTS tasks where rows meet their classes.
HOT, SALTS = 1000, 64


def _meet_classes(fps: DataFrame, of: DataFrame, sizes: DataFrame) -> DataFrame:
    """fps joined with of (g, ...) on fp = g, the rows of hot fingerprints spread; sizes: (fp, n) of every fingerprint."""
    total = sizes.agg(F.sum("n")).first()[0] or 0
    hot = [r["fp"] for r in sizes.filter(F.col("n") > max(HOT, total // HOT)).select("fp").collect()]  # HOT rows at most
    if not hot:
        return fps.join(of, F.col("fp") == F.col("g"))
    salt = F.pmod(F.xxhash64(*fps.columns), F.lit(SALTS))
    mine = fps.withColumn("salt_", F.when(F.col("fp").isin(hot), salt).otherwise(F.lit(0).cast("long")))
    every = F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))
    theirs = of.withColumn("salt_", F.explode(F.when(F.col("g").isin(hot), every).otherwise(F.array(F.lit(0).cast("long")))))
    return mine.join(theirs.withColumnRenamed("salt_", "of_"), (F.col("fp") == F.col("g")) & (F.col("salt_") == F.col("of_")))


def near_duplicate_classes(docs: DataFrame, radius: int = 2) -> DataFrame:
    """(doc_id, fp, component_id) of each row of docs; component_id: least doc_id reachable.

    Words are runs without blanks, A-Z lower-cased; fewer than three are one shingle, none (null,
    empty or blank text) give fingerprint zero, which links like any other. Rows with the same
    doc_id stay rows. A null doc_id is a component's id only if the component has no other. An
    empty table gives an empty table; further columns of docs are not read.
    """
    fps, linked = _classes(docs, radius)
    reps = fps.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("n"))  # copies are folded before any join
    classed = cut(reps.join(linked, F.col("fp") == F.col("f"), "left").select("fp", "least", "n", F.coalesce("root", "fp").alias("root")), "classes")
    heads = classed.groupBy("root").agg(F.min("least").alias("component_id"))
    of = classed.join(heads, "root").select(F.col("fp").alias("g"), "component_id")
    return _meet_classes(fps, of, classed.select("fp", "n")).select("doc_id", "fp", "component_id")


def keep_one(docs: DataFrame, radius: int = 2) -> DataFrame:
    """docs with one row of each class of near duplicates: the least doc_id, ties by the text's hash.

    Null ids are the greatest. Of wholly repeated (doc_id, text) rows one stays. Other columns pass
    through; an empty table gives an empty table.
    """
    return _first_of_each(docs, *_classes(docs, radius))


def keep_one_similar(docs: DataFrame, radius: int = 2) -> DataFrame:
    """As keep_one, but near duplicates are linked by fingerprints within radius or by a Jaccard similarity of NEAR
    or more of their shingle sets.

    The sets are those of shingles of NEAR_SHINGLE words. Texts of fewer words are one shingle;
    texts without words are copies of each other.
    """
    return _first_of_each(docs, *_near_classes(docs, radius))


def _first_of_each(docs: DataFrame, fps: DataFrame, linked: DataFrame) -> DataFrame:
    order = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "tid")
    first = fps.groupBy("fp").agg(F.min(order).alias("first"), F.count(F.lit(1)).alias("n"))
    classed = cut(first.join(linked, F.col("fp") == F.col("f"), "left").select("fp", "first", "n", F.coalesce("root", "fp").alias("root")), "classes")
    best = classed.groupBy("root").agg(F.min("first").alias("first"))
    stays = best.select("root", F.col("first.doc_id").alias("d"), F.col("first.tid").alias("t"))
    of = classed.select(F.col("fp").alias("g"), "root").join(stays, "root")
    marked = _meet_classes(fps, of, classed.select("fp", "n")).select("doc_id", "tid", (F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("tid") == F.col("t"))).alias("stays"))
    keys = cut(marked.groupBy("doc_id", "tid").agg(F.max("stays").alias("stays"), F.count(F.lit(1)).alias("n")).filter("not stays or n > 1"), "dropped")
    tid, d, t = fresh(docs, "_tid", "_d", "_t")
    keyed = docs.withColumn(tid, F.xxhash64(F.coalesce("text", F.lit(""))))
    same = F.col("doc_id").cast("long").eqNullSafe(F.col(d)) & (F.col(tid) == F.col(t))
    single = keyed.join(keys.select(F.col("doc_id").alias(d), F.col("tid").alias(t)), same, "left_anti")
    repeated = keyed.join(keys.filter("stays").select(F.col("doc_id").alias(d), F.col("tid").alias(t)), same, "left_semi").dropDuplicates(["doc_id", tid])
    return single.unionByName(repeated).drop(tid)


def hex_of(column: str):
    return F.lower(F.lpad(F.hex(F.col(column)), 16, "0"))
