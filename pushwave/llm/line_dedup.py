"""Corpus-wide removal of repeated lines (operator 5).

Line keys are hashed to 128 bits and range-partitioned by (hash, document, position), so a
line that fills a third of the corpus is spread over many partitions instead of one. Each
partition is sorted and streamed once. A run of equal hashes that lies inside a partition is
decided there; the first and the last run of a partition may go on next door, so their rows
stay open and each leaves one summary row. Summaries number at most two a partition; joined
back they settle the open rows. What comes out is a compressed keep bitmap per document; texts
are never shuffled for the decision itself.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pushwave.llm.common import LOWER, UPPER, Batches, fresh, raw, table, tidy
from pushwave.plans.durable import cut

#: Stripped from both ends of a line.
BLANKS = " \t\n\x0b\x0c\r"
DROP, OPEN, SUMMARY = 0, 1, 2
RUN_SCHEMA = "kind int, h1 long, h2 long, doc_id long, tid long, pos int, n long"
RUN_ARROW = pa.schema([("kind", pa.int32()), ("h1", pa.int64()), ("h2", pa.int64()), ("doc_id", pa.int64()), ("tid", pa.int64()), ("pos", pa.int32()), ("n", pa.int64())])
#: Stands for a null id inside the stream; it sorts below all others.
NO_ID = -(2**63)


def _identified(docs: DataFrame) -> DataFrame:
    """A row is known by its id and its text's hash, so equal ids with other texts stay apart."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("doc_id"), F.xxhash64(text).alias("tid"), text.alias("text"))


def line_hashes(docs: DataFrame, min_chars: int) -> DataFrame:
    lines = _identified(docs).select("doc_id", "tid", F.posexplode(F.split("text", "\n", -1)).alias("pos", "line"))
    key = F.translate(F.trim(F.col("line"), F.lit(BLANKS)), UPPER, LOWER)
    keyed = lines.select("doc_id", "tid", "pos", key.alias("key")).filter(F.char_length("key") >= min_chars)
    return keyed.select(F.xxhash64("key").alias("h1"), F.xxhash64(F.lit(7), F.col("key")).alias("h2"), "doc_id", "tid", "pos")


class _Run:
    """The run of equal hashes that is still going on."""

    def __init__(self, first: bool, key: tuple[int, int], top: int):
        self.first, self.key, self.top, self.n, self.last, self.held = first, key, top, 0, None, []


def _runs(min_docs: int):
    def stream(batches: Batches) -> Batches:
        run: _Run | None = None

        def rows(kind, part):
            h1, h2, d, t, p = part
            return table(RUN_ARROW, np.full(len(d), kind, np.int32), h1, h2, d, t, p, np.zeros(len(d), np.int64))

        def summary(r: _Run):
            return table(RUN_ARROW, [SUMMARY], [r.key[0]], [r.key[1]], [r.top], [0], [0], [r.n])

        def extend(r: _Run, part, docs_new):
            """Add rows of one run; yields what is decided by now."""
            r.n += int(docs_new.sum())
            r.last = (int(part[2][-1]), int(part[3][-1]))
            if r.first:
                yield rows(OPEN, part)
                return
            below = part[2] != r.top
            if below.any():
                r.held.append(tuple(c[below] for c in part))
            if r.n >= min_docs:
                for held in r.held:
                    yield rows(DROP, held)
                r.held = []

        for batch in batches:
            if not batch.num_rows:
                continue
            cols = tuple(batch.column(n).to_numpy(zero_copy_only=False) for n in ("h1", "h2", "doc_id", "tid", "pos"))
            h1, h2, d, t, _ = cols
            new_key = np.ones(len(h1), bool)
            new_key[1:] = (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])
            new_doc = new_key.copy()
            new_doc[1:] |= (d[1:] != d[:-1]) | (t[1:] != t[:-1])
            starts = np.flatnonzero(new_key)
            ends = np.append(starts[1:], len(h1))
            went_on = run is not None and run.key == (int(h1[0]), int(h2[0]))
            if went_on:
                e = int(ends[0])
                new_doc[0] = run.last != (int(d[0]), int(t[0]))
                yield from extend(run, tuple(c[:e] for c in cols), new_doc[:e])
            k = int(went_on)  # the first run that begins in this batch
            if k < len(starts):
                if run is not None and run.first:
                    yield summary(run)
                begun = run is not None
                if not begun:  # the partition's first run
                    s, e = int(starts[k]), int(ends[k])
                    run = _Run(True, (int(h1[s]), int(h2[s])), int(d[s]))
                    yield from extend(run, tuple(c[s:e] for c in cols), new_doc[s:e])
                    k += 1
                    if k < len(starts):
                        yield summary(run)
                if k < len(starts):
                    a, b = int(starts[k]), int(starts[-1])
                    if b > a:  # runs that begin and end here
                        own = starts[k:-1] - a
                        n_docs = np.add.reduceat(new_doc[a:b].astype(np.int64), own)
                        which = np.cumsum(new_key[a:b]) - 1
                        top = d[a:b][own]
                        gone = (n_docs[which] >= min_docs) & (d[a:b] != top[which])
                        if gone.any():
                            yield rows(DROP, tuple(c[a:b][gone] for c in cols))
                    run = _Run(False, (int(h1[b]), int(h2[b])), int(d[b]))
                    yield from extend(run, tuple(c[b:] for c in cols), new_doc[b:])
        if run is not None:
            for held in run.held:
                yield rows(OPEN, held)
            yield summary(run)

    return stream


def keep_bitmaps(docs: DataFrame, min_chars: int = 40, min_docs: int = 5) -> DataFrame:
    """(doc_id, tid, n_dropped, keep): keep is a zlib-packed bitmap, bit i for line i, most significant
    first; lines after its last bit are kept. Documents that lose no line have no row."""
    order = [F.col("h1"), F.col("h2"), F.col("doc_id").desc(), F.col("tid")]
    runs = line_hashes(docs, min_chars).repartitionByRange(*order).sortWithinPartitions(*order, "pos")
    told = cut(runs.mapInArrow(_runs(min_docs), RUN_SCHEMA), "line-runs")
    open_keys = told.filter(F.col("kind") == SUMMARY).groupBy("h1", "h2").agg(F.sum("n").alias("n"), F.max("doc_id").alias("top")).filter(F.col("n") >= min_docs).drop("n")
    # At most two summaries a partition: bounded by the number of partitions, not by rows.
    late = told.filter(F.col("kind") == OPEN).join(F.broadcast(open_keys), ["h1", "h2"]).filter(F.col("doc_id") < F.col("top"))
    gone = told.filter(F.col("kind") == DROP).select("doc_id", "tid", "pos").unionByName(late.select("doc_id", "tid", "pos"))
    per_doc = gone.groupBy("doc_id", "tid").agg(F.collect_set("pos").alias("gone"))  # no more than the lines of one document
    return per_doc.mapInArrow(_pack, "doc_id long, tid long, n_dropped long, keep binary")


def _pack(batches: Batches) -> Batches:
    schema = pa.schema([("doc_id", pa.int64()), ("tid", pa.int64()), ("n_dropped", pa.int64()), ("keep", pa.binary())])
    for b in batches:
        maps, counts = [], []
        for gone in b.column("gone"):
            g = np.asarray(gone.values, np.int64)
            bits = np.ones(int(g.max()) + 1, np.uint8)
            bits[g] = 0
            maps.append(zlib.compress(np.packbits(bits).tobytes(), 6) + len(bits).to_bytes(4, "little"))
            counts.append(len(g))
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("tid"), pa.array(counts, pa.int64()), pa.array(maps, pa.binary())], schema=schema)


def unpack(keep: bytes | None, n_lines: int) -> np.ndarray:
    """The bitmap as one boolean a line."""
    out = np.ones(n_lines, bool)
    if keep is not None:
        n = int.from_bytes(keep[-4:], "little")
        out[:n] = np.unpackbits(np.frombuffer(zlib.decompress(keep[:-4]), np.uint8), count=n).astype(bool)
    return out


def with_bitmaps(docs: DataFrame, min_chars: int = 40, min_docs: int = 5) -> tuple[DataFrame, str, str]:
    """Each row of docs with its number of dropped lines and its bitmap (null: every line stays), and
    the names of these two columns; other columns pass through."""
    doc, tid, d, t, n, keep = fresh(docs, "_doc", "_tid", "_d", "_t", "_n", "_keep")
    maps = keep_bitmaps(docs, min_chars, min_docs).toDF(d, t, n, keep)
    keyed = docs.withColumns({doc: F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)), tid: F.xxhash64(F.coalesce(F.col("text"), F.lit("")))})
    return keyed.join(maps, (F.col(doc) == F.col(d)) & (F.col(tid) == F.col(t)), "left").drop(doc, tid, d, t), n, keep


def _cut_text(text: bytes | None, keep: bytes | None) -> bytes | None:
    if text is None or keep is None:
        return text
    lines = text.split(b"\n")
    stay = unpack(keep, len(lines))
    return b"\n".join(x for x, k in zip(lines, stay.tolist(), strict=True) if k)


def drop_repeated_lines(docs: DataFrame, min_chars: int = 40, min_docs: int = 5) -> DataFrame:
    """docs with the repeated lines gone from text; all columns and rows stay.

    A line's key is the line without blanks at its ends, A-Z lower-cased. A key of min_chars code
    points or more that min_docs documents hold loses its lines except in the largest doc_id.
    Null text stays null and counts as one empty line. A null doc_id is below all others. Rows with
    the same doc_id and text are one document when counting; with the same doc_id and other texts
    they are several. Ties for the largest doc_id keep their lines in all of its rows. An empty
    table gives an empty table. Further columns, of any name, pass through.
    """
    names, has_chars = docs.columns, "n_chars" in docs.columns
    joined, _, keep = with_bitmaps(docs, min_chars, min_docs)

    def apply(batches: Batches) -> Batches:
        for b in batches:
            texts = [_cut_text(x, k) for x, k in zip(raw(b, "text"), b.column(keep).to_pylist(), strict=True)]
            cols = [pa.array(texts, pa.binary()).cast(pa.string()) if n == "text" else b.column(n) for n in names]
            yield pa.RecordBatch.from_arrays(cols, names=names)

    out = joined.mapInArrow(tidy(apply), docs.schema)
    return out.withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType)) if has_chars else out


def line_digest(docs: DataFrame, min_chars: int = 40, min_docs: int = 5) -> DataFrame:
    """(doc_id, n_lines, n_dropped, kept_sha256) of each row."""
    joined, dropped, keep = with_bitmaps(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), min_chars, min_docs)

    def digest(batches: Batches) -> Batches:
        schema = pa.schema([("doc_id", pa.int64()), ("n_lines", pa.int64()), ("n_dropped", pa.int64()), ("kept_sha256", pa.string())])
        for b in batches:
            n, sums = [], []
            for x, k in zip(raw(b, "text"), b.column(keep).to_pylist(), strict=True):
                x = x or b""
                n.append(x.count(b"\n") + 1)
                sums.append(hashlib.sha256(_cut_text(x, k)).hexdigest())
            yield table(schema, b.column("doc_id").to_pylist(), n, [v or 0 for v in b.column(dropped).to_pylist()], sums)

    return joined.mapInArrow(digest, "doc_id long, n_lines long, n_dropped long, kept_sha256 string")


#: What DuckDB makes of the same contract.
LINE_DEDUP_SQL = """
WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS pos FROM d),
k AS (SELECT doc_id, pos, line, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
        'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
hot AS (SELECT key, max(doc_id) AS top FROM k WHERE length(key) >= 40 GROUP BY key HAVING count(DISTINCT doc_id) >= 5),
f AS (SELECT k.doc_id, k.pos, k.line, (hot.key IS NOT NULL AND k.doc_id <> hot.top) AS gone FROM k LEFT JOIN hot ON k.key = hot.key)
SELECT doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (WHERE gone)::BIGINT AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM f GROUP BY doc_id
"""
