"""Removal of word passages that an earlier document holds too, by seed and extend.

Seeds.  Every window of ``window`` words selects one of its ``anchor``-word grams,
the one with the least hash (winnowing).  Equal windows select the same gram at the
same offset, so documents that share a window meet at that anchor.  Only anchors
found in two documents at least go on.

Extension.  Around an anchor, the windows that selected it form one stretch.  Its
extent to both sides, and a hash of all its words, are known from the document
alone.  Where a smaller document has the same stretch, the whole of it matches and
nothing more need be compared.  Only the first documents of stretches that differ
around a common anchor are compared window by window, so a group of many copies
costs its size, not its square.

Maximal repeats.  Matching windows of a document that touch are merged into spans;
each word inside a span is removed.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .frames import Workspace
from .key_filter import KeyFilter, key_filter
from .textkernel import _BASE, _BASE_INVERSE, Words, _powers, gram_hashes, mix64, row_slices, string_buffers

#: A key with more rows than this, and than a ten-thousandth of all, is spread over several tasks.
HOT_ROWS = 50_000
_OTHER_WORDS = np.uint64(0xD6E8FEB86659FD93)


def _stretches(words: Words, window: int, anchor: int) -> tuple[np.ndarray, ...]:
    """(row, first window, windows, anchor hash, context hash) of all anchors of the rows.

    Window numbers count words from the start of their own row.
    """
    h = words.hashes()
    n = len(h) - window + 1
    if n <= 0:
        return (np.zeros(0, np.int64),) * 3 + (np.zeros(0, np.uint64),) * 2
    starts = np.flatnonzero(words.row[:n] == words.row[window - 1 :])
    if not len(starts):
        return (np.zeros(0, np.int64),) * 3 + (np.zeros(0, np.uint64),) * 2
    grams = gram_hashes(h, anchor)
    least, at = grams[starts], starts.copy()
    for j in range(1, window - anchor + 1):
        other = grams[starts + j]
        lower = other < least
        least = np.where(lower, other, least)
        at = np.where(lower, starts + j, at)
    new = np.empty(len(starts), dtype=bool)
    new[0] = True
    new[1:] = (at[1:] != at[:-1]) | (starts[1:] != starts[:-1] + 1)
    head = np.flatnonzero(new)
    count = np.diff(np.append(head, len(starts)))
    first = starts[head]
    running = np.zeros(len(h) + 1, dtype=np.uint64)
    np.cumsum(h * _powers(_BASE, len(h)), out=running[1:])
    inside = (running[first + count + window - 1] - running[first]) * _powers(_BASE_INVERSE, len(h) + 1)[first]
    context = mix64(inside + (count * 64 + (at[head] - first)).astype(np.uint64))
    row = words.row[first]
    return row, first - words.first[row], count, least[head], context


def _scan(docs: DataFrame, window: int, anchor: int, stretches: bool) -> DataFrame:
    """Anchors of every document: (anchor, doc_id), or with their stretches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, marks = batch.column(0).to_numpy(), batch.column(2).to_numpy()
            offsets, raw = string_buffers(batch.column(1))
            for a, b in row_slices(offsets):
                row, first, count, seed, context = _stretches(Words(offsets, raw, a, b), window, anchor)
                if stretches:
                    columns = [seed.view(np.int64), context.view(np.int64), ids[a:b][row], marks[a:b][row], first.astype(np.int32), count.astype(np.int8)]
                    names = ["anchor", "context", "doc_id", "mark", "first", "n"]
                else:
                    once = np.unique(np.rec.fromarrays([seed.view(np.int64), row])) if len(row) else np.rec.fromarrays([seed.view(np.int64), row])
                    columns, names = [np.ascontiguousarray(once.f0), ids[a:b][once.f1]], ["anchor", "doc_id"]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=names)

    return docs.mapInArrow(run, "anchor long, context long, doc_id long, mark int, first int, n byte" if stretches else "anchor long, doc_id long")


def _windows(docs: DataFrame, window: int) -> DataFrame:
    """(w1, w2, doc_id, mark, first) of the windows in listed stretches of each document; two hashes tell windows apart."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, marks = batch.column(0).to_numpy(), batch.column(2).to_numpy()
            offsets, raw = string_buffers(batch.column(1))
            for k in range(batch.num_rows):
                h = Words(offsets, raw, k, k + 1).hashes()
                at = np.unique(np.concatenate([np.arange(s["first"], s["first"] + s["n"]) for s in batch.column(3)[k].as_py()]))
                both = [gram_hashes(x, window)[at].view(np.int64) for x in (h, mix64(h ^ _OTHER_WORDS))]
                yield pa.RecordBatch.from_arrays(
                    [*map(pa.array, both), pa.array(np.full(len(at), ids[k])), pa.array(np.full(len(at), marks[k], dtype=np.int32)), pa.array(at.astype(np.int32))], names=["w1", "w2", "doc_id", "mark", "first"]
                )

    return docs.mapInArrow(run, "w1 long, w2 long, doc_id long, mark int, first int")


def with_lookup(rows: DataFrame, lookup: DataFrame, keys: list[str], spread_by: list[str]) -> DataFrame:
    """``rows`` joined with the one row that ``lookup`` (keys, rows_of_key, ...) has of their keys.

    Hot keys are dealt over several tasks: their rows by a hash of ``spread_by``, their
    row of the lookup once for each part.  There are at most ten thousand of them.
    """
    total = lookup.agg(F.coalesce(F.sum("rows_of_key"), F.lit(0))).first()[0]
    limit = max(HOT_ROWS, total // 10_000)
    hot = lookup.where(F.col("rows_of_key") > limit).select(*keys, F.ceil(F.col("rows_of_key") / limit).cast("int").alias("parts"))
    if hot.isEmpty():
        return rows.join(lookup.drop("rows_of_key"), keys)
    parts = F.coalesce("parts", F.lit(1))
    dealt = rows.join(F.broadcast(hot), keys, "left").withColumn("part", F.pmod(F.xxhash64(*spread_by), parts).cast("int")).drop("parts")  # total / limit rows at most
    every_part = F.sequence(F.lit(0), F.greatest(F.lit(1), F.when(F.col("rows_of_key") > limit, F.ceil(F.col("rows_of_key") / limit)).otherwise(1)).cast("int") - 1)
    copied = lookup.withColumn("part", F.explode(every_part))
    return dealt.join(copied.drop("rows_of_key"), [*keys, "part"]).drop("part")


def _listed(docs: DataFrame, listed: KeyFilter) -> DataFrame:
    """Documents (doc_id, text, mark) whose id may be listed; the others need not travel."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(listed.has(batch.column(3).to_numpy()))).select([0, 1, 2])

    return docs.select("doc_id", "text", "mark", F.xxhash64("doc_id").alias("h")).mapInArrow(run, "doc_id long, text string, mark int")


def find_repeats(docs: DataFrame, window: int, anchor: int, work: Workspace) -> DataFrame:
    """(doc_id, mark, spans): runs of windows (first, n) that a smaller id holds too."""
    count = F.count(F.lit(1)).alias("rows_of_key")
    seeds = _scan(docs, window, anchor, False).groupBy("anchor").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi"), count).where("lo < hi")
    seeds = work.keep(seeds.select("anchor", "rows_of_key"), "seeds", release=True)
    shared = work.keep(with_lookup(_scan(docs, window, anchor, True), seeds, ["anchor"], ["doc_id", "first"]), "shared", release=True)
    work.forget("seeds")
    classes = work.keep(shared.groupBy("anchor", "context").agg(F.min("doc_id").alias("lo"), count), "classes", release=True)
    whole = with_lookup(shared, classes, ["anchor", "context"], ["doc_id", "first"])
    matched = whole.where("doc_id > lo").select("doc_id", "mark", "first", "n")
    # first documents of stretches around anchors with several different stretches
    several = classes.groupBy("anchor").agg(F.min("context").alias("a"), F.max("context").alias("b")).where("a <> b").select("anchor")
    firsts = shared.join(classes.select("context", "anchor", F.col("lo").alias("doc_id")), ["anchor", "context", "doc_id"])
    heads = work.keep(firsts.join(several, "anchor").groupBy("doc_id", "mark").agg(F.collect_set(F.struct("first", "n")).alias("s")), "heads")
    listed = _listed(docs, key_filter(heads.select(F.xxhash64("doc_id").alias("h")), "h"))
    windows = work.keep(_windows(listed.join(heads, ["doc_id", "mark"]).select("doc_id", "text", "mark", "s"), window), "windows", release=True)
    least = windows.groupBy("w1", "w2").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).where("lo < hi")
    single = windows.join(least, ["w1", "w2"]).where("doc_id > lo").select("doc_id", "mark", "first", F.lit(1).cast("byte").alias("n"))
    return matched.unionByName(single).groupBy("doc_id", "mark").agg(F.collect_list(F.struct("first", "n")).alias("spans"))


def merged(spans: list[tuple[int, int]], window: int) -> list[tuple[int, int]]:
    """Maximal word spans (start, end) that runs of windows cover."""
    out: list[tuple[int, int]] = []
    for first, n in sorted(spans):
        end = first + n - 1 + window
        if out and first <= out[-1][1]:
            out[-1] = (out[-1][0], max(end, out[-1][1]))
        else:
            out.append((first, end))
    return out


def remove_repeats(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", *, window: int = 13, anchor: int = 5, with_text: bool = False) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256[, repeats, kept_text]) for every row.

    A word is a run of characters outside 0x20 and 0x09-0x0D.  Removed is each word
    inside a window of ``window`` words that also starts in a row with a smaller id;
    windows are judged on the input.  Null and empty texts have no words.  Rows with
    a null id keep all words and are no source for others.  Rows that repeat an id
    never remove each other's words.  Texts of any length are judged whole.  Other
    columns are not read, whatever their names; ties cannot occur; an empty table gives
    no row.
    """
    docs = df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.hash(F.col(text_col).cast("string")).alias("mark"))
    work = Workspace(df.sparkSession, "repeats")
    found = work.keep(find_repeats(docs.where(F.col("doc_id").isNotNull() & F.col("text").isNotNull()), window, anchor, work), "spans", release=True)
    work.forget_all_but("spans")
    listed = key_filter(found.select(F.xxhash64("doc_id").alias("h")), "h")
    fields = [("n_words", T.LongType()), ("n_removed", T.LongType()), ("kept_sha256", T.StringType())]
    if with_text:
        fields += [("repeats", T.ArrayType(T.StructType([T.StructField("start", T.IntegerType()), T.StructField("end", T.IntegerType())]))), ("kept_text", T.StringType())]
    types = (pa.int64(), pa.int64(), pa.string(), pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())])), pa.string())[: len(fields)]

    def judged(text: str | None, spans: list) -> tuple:
        words = (text or "").encode().split()
        repeats = merged([(s["first"], s["n"]) for s in spans], window)
        kept, at = [], 0
        for a, b in repeats:
            kept += words[at:a]
            at = b
        body = b" ".join(kept + words[at:])
        return len(words), sum(b - a for a, b in repeats), hashlib.sha256(body).hexdigest(), [{"start": a, "end": b} for a, b in repeats], body.decode() if with_text else None

    def early(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # rows without repeats are finished here and travel without their text
        for batch in batches:
            wait = listed.has(batch.column(3).to_numpy()) & ~np.asarray(batch.column(0).is_null())
            texts = [x.as_py() for x in batch.column(1)]
            done = [None if w else judged(t, []) for w, t in zip(wait.tolist(), texts, strict=True)]
            columns = [batch.column(0), batch.column(2), pa.array([t if w else None for w, t in zip(wait.tolist(), texts, strict=True)], pa.string()), pa.array(wait)]
            columns += [pa.array([d and d[i] for d in done], t) for i, t in enumerate(types)]
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "mark", "text", "wait", *[n for n, _ in fields]])

    first = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("mark", T.IntegerType()), T.StructField("text", T.StringType()), T.StructField("wait", T.BooleanType()), *[T.StructField(n, t) for n, t in fields]])
    rows = docs.select("doc_id", "text", "mark", F.xxhash64("doc_id").alias("h")).mapInArrow(early, first).join(found, ["doc_id", "mark"], "left")

    def late(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            col = dict(zip(batch.schema.names, batch.columns, strict=True))
            out = []
            for k, wait in enumerate(col["wait"].to_pylist()):
                out.append(judged(col["text"][k].as_py(), col["spans"][k].as_py() or []) if wait else tuple(col[n][k].as_py() for n, _ in fields))
            yield pa.RecordBatch.from_arrays([col["doc_id"], *[pa.array([o[i] for o in out], t) for i, t in enumerate(types)]], names=["doc_id", *[n for n, _ in fields]])

    return rows.mapInArrow(late, T.StructType([first["doc_id"], *[T.StructField(n, t) for n, t in fields]]))
