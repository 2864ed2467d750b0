"""Exact self-join of documents by Jaccard similarity of word shingles.

Prefixes.  All shingles follow one global order: first those that few documents
have, by hash; then the frequent ones, by their number of documents.  If x and y are
similar they share at least t(x) = ceil(s * |x|) shingles, so the first
|x| - t(x) + l shingles of both hold l common ones at least.  Each document chooses
its own l: a longer prefix costs more postings but demands more matches, and the l
with the least estimated cost, from the document counts of the prefix, is taken.  A
pair that needs an overlap of o by its sizes has to share, in the two prefixes,
min(o - t(x) + l(x), o - t(y) + l(y)) shingles before it is verified.  Neither can
share more than it meets with any node, so a pair whose demand is above that is left
out before its common shingles are counted; one side alone bounds nothing, as the
other prefix may end first.

Copies.  Equal shingle sets are one node.  Near copies would meet in all pairs, so
before the join each node is compared with one centre, the node most of its
shared prefix shingles elect: each elects the most typical of its nodes, whose
shingles most documents have (in later rounds, any).  Verified pairs are contracted to components, and only
shingles that still join different components emit pairs.  Every pair of different
components that shares enough prefix shingles is verified, so no link between
components is lost; pairs inside a component cannot change the result.

Verification compares whole sets (sorted 40-bit shingle codes).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected
from .frames import Workspace, small_batches, tidied
from .key_filter import KeyFilter, key_filter
from .textkernel import Words, row_slices, shingle_sets, string_buffers


@dataclass(frozen=True)
class Similarity:
    """Shingle length in words and the similarity in hundredths."""

    words: int
    percent: int

    def overlap(self, n: int) -> int:
        """Fewest shingles that a set of n shares with any similar set."""
        return -(-self.percent * n // 100)


def _node(shingles: np.ndarray) -> int:
    """Signed 64-bit identity of a shingle set."""
    return int(np.uint64(xxhash.xxh3_64_intdigest(shingles.tobytes(), seed=len(shingles))).view(np.int64))


def _sets(batch: pa.RecordBatch, words: int):
    """(row, shingle set) of every row of a batch (doc_id, text)."""
    offsets, raw = string_buffers(batch.column(1))
    for a, b in row_slices(offsets):
        yield from enumerate(shingle_sets(Words(offsets, raw, a, b, lower=True), words), a)


def _code(shingles: np.ndarray, bits: int) -> np.ndarray:
    """Leading 32 + bits bits of shingle hashes."""
    return shingles >> np.uint64(32 - bits)


_SCANNED = "doc_id long, n long, node long, code long, df long"


def scanned(docs: DataFrame, words: int, work: Workspace, *, least: int = 16, flush: int = 1 << 20) -> tuple[int, DataFrame]:
    """(bits, rows) of one pass over all texts: (doc_id, n, node) of every row and (code, df) of frequent shingles.

    Counts are of documents that have an id, exact by code of 32 + bits bits.  Map tasks
    count what they have read and ship sorted codes by range, so a shingle of every
    document costs one entry a task; facts of documents travel in the same groups.  Codes
    of fewer than ``least`` documents stay behind.
    """
    size = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    bits = int(min(20, max(4, np.ceil(np.log2(max(size, 1) / (6 << 20))))))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        size = 0

        def flushed() -> pa.RecordBatch:
            codes, counts = np.unique(np.concatenate(held), return_counts=True)
            ranges = (codes >> np.uint64(32)).astype(np.int64)
            at = np.flatnonzero(np.append(True, ranges[1:] != ranges[:-1]))
            tails, sums = codes.astype(np.uint32), counts.astype(np.uint32)
            ends = np.append(at[1:], len(codes))
            small = [sums[a:b].max() < 256 for a, b in zip(at, ends, strict=True)]
            return pa.RecordBatch.from_arrays(
                [
                    pa.array(ranges[at].astype(np.int32)),
                    pa.array([tails[a:b].tobytes() for a, b in zip(at, ends, strict=True)], pa.binary()),
                    pa.array([(sums[a:b].astype(np.uint8) if s else sums[a:b]).tobytes() for a, b, s in zip(at, ends, small, strict=True)], pa.binary()),
                    pa.nulls(len(at), pa.binary()),
                ],
                names=["range", "tails", "counts", "facts"],
            )

        for batch in batches:
            found = []
            named = np.asarray(batch.column(0).is_valid())
            for k, s in _sets(batch, words):
                found.append((len(s), _node(s)))
                if len(s) and named[k]:
                    held.append(_code(s, bits))
                    size += len(s)
                if size >= flush:
                    yield flushed()
                    held, size = [], 0
            if found:
                facts = pa.RecordBatch.from_arrays([batch.column(0), pa.array([f[0] for f in found], pa.int64()), pa.array([f[1] for f in found], pa.int64())], names=["doc_id", "n", "node"])
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, facts.schema) as stream:
                    stream.write_batch(facts)
                where = -1 - found[0][1] % (1 << bits)
                yield pa.RecordBatch.from_arrays([pa.array([where], pa.int32()), pa.nulls(1, pa.binary()), pa.nulls(1, pa.binary()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], names=["range", "tails", "counts", "facts"])
        if held:
            yield flushed()

    def total_up(part: pa.Table) -> pa.Table:
        if part.column("range")[0].as_py() < 0:
            facts = pa.concat_tables([pa.ipc.open_stream(x.as_py()).read_all() for x in part.column("facts")])
            return facts.append_column("code", pa.nulls(len(facts), pa.int64())).append_column("df", pa.nulls(len(facts), pa.int64()))
        tails = np.concatenate([np.frombuffer(x.as_py(), np.uint32) for x in part.column("tails")])
        counts = np.concatenate([np.frombuffer(c.as_py(), np.uint8 if len(c.as_py()) * 4 == len(t.as_py()) else np.uint32).astype(np.int64) for t, c in zip(part.column("tails"), part.column("counts"), strict=True)])
        order = np.argsort(tails, kind="stable")
        tails, counts = tails[order], counts[order]
        at = np.flatnonzero(np.append(True, tails[1:] != tails[:-1]))
        sums = np.add.reduceat(counts, at)
        often = sums >= least
        high = np.int64(part.column("range")[0].as_py()) << np.int64(32)
        codes = tails[at][often].astype(np.int64) + high
        return pa.table({**{c: pa.nulls(len(codes), pa.int64()) for c in ("doc_id", "n", "node")}, "code": pa.array(codes), "df": pa.array(sums[often].astype(np.int64))})

    found = docs.mapInArrow(tidied(count), "range int, tails binary, counts binary, facts binary").groupBy("range").applyInArrow(total_up, _SCANNED)
    return bits, work.keep(found, "scan", release=True)


def frequent_shingles(scan: DataFrame, most: int = 1 << 18) -> tuple[np.ndarray, np.ndarray]:
    """(codes, counts) of the shingles that most documents have, ``most`` of them at the most.

    They steer the order of the join alone, which gives the same links under any order.
    """
    top = scan.where("code IS NOT NULL").select("code", "df").orderBy(F.desc("df"), "code").limit(most).toArrow()
    codes, counts = top.column("code").to_numpy(), top.column("df").to_numpy()
    order = np.argsort(codes)
    return codes[order].astype(np.uint64), counts[order].astype(np.int64)


_STEPS = (1, 2, 3, 4, 6, 8, 12, 16)


def chosen_prefix(shingles: np.ndarray, counts: np.ndarray, similarity: Similarity) -> tuple[np.ndarray, int]:
    """(prefix shingles, demanded matches l) of one document, given the document counts of its shingles.

    The estimated cost of l is one unit a posting and, for the candidates that a
    prefix leads to, their number divided by l squared: candidates that share only a
    passage fall away as more matches are demanded.
    """
    n = len(shingles)
    t = similarity.overlap(n)
    if not counts.any():
        return shingles[: n - t + 1], 1
    order = np.argsort(counts, kind="stable")
    sums = np.cumsum(counts[order])
    steps = [x for x in _STEPS if x <= t]
    best = min(steps, key=lambda x: (n - t + x + 4.0 * sums[n - t + x - 1] / (x * x), x))
    return shingles[order[: n - t + best]], best


class _Order:
    """Prefixes of shingle sets in the global order."""

    def __init__(self, similarity: Similarity, frequent: tuple[int, np.ndarray, np.ndarray]):
        self.similarity, (self.bits, self.codes, self.often) = similarity, frequent

    def prefix(self, shingles: np.ndarray) -> tuple[np.ndarray, int, int]:
        """(prefix shingles, demanded matches l, how typical the set is: 16 times its mean document count)."""
        counts = np.zeros(len(shingles), np.int64)
        if len(self.codes):
            own = _code(shingles, self.bits)
            at = np.minimum(np.searchsorted(self.codes, own), len(self.codes) - 1)
            counts = np.where(self.codes[at] == own, self.often[at], 0)
        prefix, demanded = chosen_prefix(shingles, counts, self.similarity)
        return prefix, demanded, int(min(16 * counts.mean(), 2**31 - 1))


def _signatures(docs: DataFrame, order: _Order) -> DataFrame:
    """(node, n, l, w, tokens) of every node: size, demand, weight and prefix; a task emits a node once."""

    def packed(out: list[tuple]) -> pa.RecordBatch:
        ends = np.cumsum([0, *[len(o[4]) for o in out]]).astype(np.int32)
        tokens = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([o[4] for o in out]).view(np.int64)))
        return pa.RecordBatch.from_arrays([*[pa.array([o[i] for o in out], t) for i, t in enumerate((pa.int64(), pa.int32(), pa.int8(), pa.int32()))], tokens], names=["node", "n", "l", "w", "tokens"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for batch in batches:
            out: list[tuple] = []
            size = 0
            for _, s in _sets(batch, order.similarity.words):
                node = _node(s)
                if len(s) and node not in seen:
                    seen.add(node)
                    prefix, demanded, typical = order.prefix(s)
                    out.append((node, len(s), demanded, typical, prefix))
                    size += len(prefix)
                if size > 200_000:
                    yield packed(out)
                    out, size = [], 0
            if out:
                yield packed(out)

    return docs.mapInArrow(tidied(run), "node long, n int, l byte, w int, tokens array<long>")


def _set_table(docs: DataFrame, words: int, wanted: KeyFilter, holders: KeyFilter) -> DataFrame:
    """(node, n, low, high) of wanted nodes, once each: size and 40-bit codes.

    ``holders`` knows one document of every wanted node; no other text is read.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for whole in batches:
            batch = whole.filter(pa.array(holders.has(whole.column(2).to_numpy())))
            out = []
            for _, s in _sets(batch, words) if batch.num_rows else ():
                node = _node(s)
                if len(s) and node not in seen and wanted.has(np.array([node]))[0]:
                    seen.add(node)
                    code = s >> np.uint64(24)
                    out.append((node, len(s), code.astype(np.uint32).tobytes(), (code >> np.uint64(32)).astype(np.uint8).tobytes()))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], t) for i, t in enumerate((pa.int64(), pa.int32(), pa.binary(), pa.binary()))], names=["node", "n", "low", "high"])

    return docs.select("doc_id", "text", F.xxhash64("doc_id").alias("h")).mapInArrow(tidied(run), "node long, n int, low binary, high binary").dropDuplicates(["node"])


def _verified(pairs: DataFrame, sets: DataFrame, similarity: Similarity) -> DataFrame:
    """Those of the pairs (a, b) whose whole sets are similar."""
    side = lambda c: sets.select(F.col("node").alias(c), *[F.col(x).alias(f"{c}_{x}") for x in ("n", "low", "high")])
    both = pairs.select("a", "b").join(side("a"), "a").join(side("b"), "b").select("a", "b", "a_n", "b_n", "a_low", "a_high", "b_low", "b_high")

    def codes(low: bytes, high: bytes) -> np.ndarray:
        return np.frombuffer(low, np.uint32).astype(np.uint64) | (np.frombuffer(high, np.uint8).astype(np.uint64) << np.uint64(32))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            similar = []
            n_a, n_b = batch.column(2).to_pylist(), batch.column(3).to_pylist()
            low_a, high_a, low_b, high_b = (batch.column(i) for i in range(4, 8))
            for k in range(batch.num_rows):
                both_codes = np.concatenate([codes(low_a[k].as_py(), high_a[k].as_py()), codes(low_b[k].as_py(), high_b[k].as_py())])
                both_codes.sort(kind="stable")
                common = int(np.count_nonzero(both_codes[1:] == both_codes[:-1]))
                similar.append(100 * common >= similarity.percent * (n_a[k] + n_b[k] - common))
            keep = pa.array(similar, pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(keep), batch.column(1).filter(keep)], names=["a", "b"])

    return both.mapInArrow(tidied(run), "a long, b long")


def _in_range(n: str, m: str, similarity: Similarity):
    """Sizes that two similar sets can have."""
    low, high = F.least(n, m).cast("long"), F.greatest(n, m).cast("long")
    return low * 100 >= high * similarity.percent


def _demanded(similarity: Similarity):
    """Common prefix shingles that a similar pair of sizes n, m and own demands l, k must have."""
    own = lambda n: f"ceil({n} * {similarity.percent} / 100.0D)"
    overlap = f"ceil((n + m) * {similarity.percent} / {100.0 + similarity.percent}D - 1e-9D)"
    return F.expr(f"least({overlap} - {own('n')} + l, {overlap} - {own('m')} + k)")


def _common(x: np.ndarray, x_sizes: np.ndarray, y: np.ndarray, y_sizes: np.ndarray, step: int = 4096) -> np.ndarray:
    """Common tokens of every list of one side with every list of the other, ``step`` tokens at a time."""
    common = np.intersect1d(x, y)
    out = np.zeros((len(x_sizes), len(y_sizes)), dtype=np.float32)
    sides = []
    for tokens, sizes in ((x, x_sizes), (y, y_sizes)):
        at = np.minimum(np.searchsorted(common, tokens), max(0, len(common) - 1))
        hit = common[at] == tokens if len(common) else np.zeros(len(tokens), bool)
        owner, at = np.repeat(np.arange(len(sizes)), sizes)[hit], at[hit]
        order = np.argsort(at, kind="stable")
        sides.append((owner[order], at[order], len(sizes)))
    for low in range(0, len(common), step):
        grid = []
        for owner, at, n in sides:
            a, b = np.searchsorted(at, (low, low + step))
            g = np.zeros((n, min(step, len(common) - low)), dtype=np.float32)
            g[owner[a:b], at[a:b] - low] = 1
            grid.append(g)
        out += grid[0] @ grid[1].T
    return out


def _hot_pairs(rows: DataFrame, hot: DataFrame, similarity: Similarity, block: int = 512) -> DataFrame:
    """Candidates (a, b) that meet in hot shingles, judged in blocks of nodes before any pair is emitted.

    Each node brings its open prefix shingles; a block of nodes meets another of the
    same shingle in one matrix product, which gives all common counts at once.
    """
    held = rows.groupBy("node").agg(F.collect_list("token").alias("tokens"))
    brought = rows.join(hot.select("token", "pairs"), "token").join(held, "node")
    # a block has about ``block`` nodes, and fewer where they bring many shingles
    load = brought.groupBy("token").agg(F.max("pairs").alias("pairs"), F.sum(F.size("tokens")).alias("load"))
    spread = F.greatest(F.lit(1), F.ceil(F.sqrt(2 * F.col("pairs")) / block), F.ceil(F.col("load") / (block * 256))).cast("int")
    member = brought.drop("pairs").join(load.select("token", spread.alias("blocks")), "token").select("token", "blocks", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int").alias("block"), F.struct("node", "n", "l", "root", "met", "tokens").alias("m"))
    blocks = member.groupBy("token", "blocks", "block").agg(F.collect_list("m").alias("m"))
    # every pair of blocks is a key of its own, so the pairs of one shingle spread over all tasks
    rows_of = blocks.select("token", "block", F.explode(F.sequence("block", F.col("blocks") - 1)).alias("other"), "m")
    columns_of = blocks.select("token", F.explode(F.sequence(F.lit(0), F.col("block"))).alias("block"), F.col("block").alias("other"), F.col("m").alias("m2"))
    both = rows_of.join(columns_of, ["token", "block", "other"]).select("m", "m2")
    share = similarity.percent / (100.0 + similarity.percent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                sides = []
                for c in (0, 1):
                    m = batch.column(c)[k].values
                    field_of = lambda name, m=m: m.field(name).to_numpy(zero_copy_only=False)
                    lists = m.field("tokens")
                    sides.append(({n: field_of(n) for n in ("node", "n", "l", "root", "met")}, lists.flatten().to_numpy(), np.diff(np.asarray(lists.offsets))))
                (x, x_tokens, x_sizes), (y, y_tokens, y_sizes) = sides
                met = _common(x_tokens, x_sizes, y_tokens, y_sizes)
                n, m = x["n"][:, None].astype(np.int64), y["n"][None, :].astype(np.int64)
                overlap = np.ceil((n + m) * share - 1e-9)
                own = lambda v: np.ceil(v * similarity.percent / 100.0)
                needed = np.minimum(overlap - own(n) + x["l"][:, None], overlap - own(m) + y["l"][None, :])
                fits = (met >= needed) & (x["root"][:, None] != y["root"][None, :]) & (np.minimum(n, m) * 100 >= np.maximum(n, m) * similarity.percent)
                i, j = np.nonzero(fits)
                a, b = x["node"][i], y["node"][j]
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], names=["a", "b"])

    return both.mapInArrow(tidied(run), "a long, b long").distinct()


def similar_groups(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", *, words: int = 5, percent: int = 80, rounds: int = 4, pairs_per_node: int = 4, hot_pairs: int = 10_000) -> DataFrame:
    """(doc_id, n_shingles, component_id) for every row.

    Words are runs of characters outside 0x20 and 0x09-0x0D, A-Z in lower case.  A
    row's set holds its distinct ``words``-word shingles; a shorter text is one
    shingle; null and empty texts have none and link with nothing.  Two rows link
    when 100 * intersection >= percent * union.  component_id is the smallest id that
    links reach.  Rows that repeat an id are one document: they share its links.  A
    null id gets a null component and links nothing; an empty row is its own component.
    Texts of any length are compared whole; equal texts cost one node.  Other columns are
    not read, whatever their names; an empty table gives no row.
    """
    spark = df.sparkSession
    similarity, work = Similarity(words, percent), Workspace(spark, "ngram-join")
    docs = df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    with small_batches(spark):
        bits, scan = scanned(docs, words, work)
    facts = scan.where("node IS NOT NULL").select("doc_id", "n", "node")
    named = docs.where(F.col("doc_id").isNotNull() & F.col("text").isNotNull())
    order = _Order(similarity, (bits, *frequent_shingles(scan)))
    signatures = work.keep(_signatures(named, order), "signatures")
    prefixes = signatures.select(F.explode("tokens").alias("token"), "node")
    met = prefixes.groupBy("token").agg(F.min("node").alias("lo"), F.max("node").alias("hi")).where("lo <> hi").select("token")
    postings = work.keep(prefixes.join(met, "token").dropDuplicates(["token", "node"]), "postings", release=True)
    met_counts = work.keep(postings.groupBy("node").agg(F.count(F.lit(1)).alias("met")), "met")
    wanted = met_counts.count()
    nodes = work.keep(met_counts.join(signatures.select("node", "n", "l", "w").dropDuplicates(["node"]), "node").select("node", "n", "l", "w", "met"), "nodes", release=True)
    work.forget("signatures")
    holders = facts.where("doc_id IS NOT NULL").join(met_counts.select("node"), "node").groupBy("node").agg(F.min("doc_id").alias("doc_id")).select(F.xxhash64("doc_id").alias("h"))
    sets = work.keep(_set_table(named, words, key_filter(met_counts, "node"), key_filter(work.keep(holders, "holders"), "h")), "sets", release=True)
    possible = _demanded(similarity) <= F.least("met", "reach")

    known = facts.where("n > 0 AND doc_id IS NOT NULL")
    first = known.groupBy("doc_id").agg(F.min("node").alias("a"), F.max("node").alias("z")).where("a <> z")
    links = work.keep(known.join(first, "doc_id").where("node <> a").select("a", F.col("node").alias("b")), "links-repeated")
    labels = connected(links, work, "cc-repeated")
    step = gained = 0
    while wanted:
        known_nodes = nodes.join(labels, "node", "left").select("node", "n", "l", "w", "met", F.coalesce("root", "node").alias("root"))
        placed = postings.join(known_nodes, "node").select("token", "node", "n", "l", "w", "met", "root")
        counted = placed.groupBy("token", "root").count().groupBy("token").agg(F.sum("count").alias("n"), F.sum(F.col("count") * F.col("count")).alias("s"), F.count(F.lit(1)).alias("roots")).where("roots > 1")
        open_tokens = work.keep(counted.select("token", ((F.col("n") * F.col("n") - F.col("s")) / 2).alias("pairs")), f"open-{step}")
        ahead = open_tokens.agg(F.coalesce(F.sum("pairs"), F.lit(0))).first()[0]
        rows = work.keep(placed.join(open_tokens.select("token"), "token"), f"rows-{step}", release=True)
        if not ahead:
            break
        last = step >= rounds or ahead <= pairs_per_node * wanted or (step > 0 and gained < wanted // 100)
        if last:
            hot = open_tokens.where(F.col("pairs") >= hot_pairs)
            cold = rows.join(hot.select("token"), "token", "left_anti")
            other = cold.select("token", F.col("node").alias("b"), F.col("n").alias("m"), F.col("l").alias("k"), F.col("root").alias("other"), F.col("met").alias("reach"))
            met = cold.withColumnRenamed("node", "a").join(other, "token").where("a < b AND root <> other").where(_in_range("n", "m", similarity)).where(possible)
            pairs = met.groupBy("a", "b").agg(F.count(F.lit(1)).alias("common"), F.first(_demanded(similarity)).alias("demanded")).where("common >= demanded")
            pairs = pairs.select("a", "b").unionByName(_hot_pairs(rows, hot, similarity)).distinct()
        else:
            typical = F.col("w") if step < 2 else F.lit(0)
            centre = rows.groupBy("token").agg(F.max_by(F.struct("node", "n", "l", "root", "met"), F.struct(typical, F.xxhash64("node", F.lit(step)))).alias("c"))
            facing = rows.join(centre, "token").where("root <> c.root").select("node", "n", "l", "met", F.col("c.node").alias("centre"), F.col("c.n").alias("m"), F.col("c.l").alias("k"), F.col("c.met").alias("reach"))
            near = facing.where(_in_range("n", "m", similarity)).where(possible)
            votes = near.groupBy("node", "centre").count()
            pairs = votes.groupBy(F.col("node").alias("a")).agg(F.max_by("centre", F.struct("count", "centre")).alias("b"))
        found = work.keep(_verified(work.keep(pairs.select("a", "b"), f"pairs-{step}"), sets, similarity), f"links-{step}")
        gained = found.count()
        links = work.keep(links.unionByName(found), f"all-{step}")
        labels = connected(links, work, f"cc-{step}")
        work.forget(f"rows-{step}", f"pairs-{step}")
        step += 1
        if last:
            break
    placed = facts.join(labels, "node", "left").withColumn("root", F.when(F.col("n") > 0, F.coalesce("root", "node")))
    least = placed.where("root IS NOT NULL AND doc_id IS NOT NULL").groupBy("root").agg(F.min("doc_id").alias("least"))
    own = placed.join(least, "root", "left").withColumn("component", F.when(F.col("doc_id").isNotNull(), F.coalesce("least", "doc_id")))
    out = work.keep(own.select("doc_id", F.col("n").alias("n_shingles"), F.col("component").alias("component_id")), "groups", release=True)
    work.forget_all_but("groups")
    return out
