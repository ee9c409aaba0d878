"""SimHash fingerprints and a binary-trie self-join within a Hamming budget.

Fingerprints are linked in three rotations of the trie. Two fingerprints that
differ in at most `budget` of 64 bits agree on at least one of budget + 1
blocks of bits; each rotation puts another block on top, deals the trie out by
that block, and a task then walks its subtrie against itself: pairs of nodes
go down together, the bits on which they differ add up, and a pair is dropped
once it has more than the budget.

A subtrie's links are reduced to a forest while it is walked: pairs of nodes
whose leaves already hang together are not opened, so a large cloud of
near-equal fingerprints costs no quadratic number of links. A block value that
holds more than `bound` fingerprints is dealt out again by the blocks of its
remaining bits.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cityweave.operators.components import components
from cityweave.llm.kernel import LOWER_TABLE, blocks, mapped
from cityweave.scratch import Scratch

WIDTH = 64
#: Rows of the frontier that are opened at once.
FRONTIER = 1 << 19


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """Bitwise majority of the XXH64 values (seed 42) of a text's word shingles; 0 without words."""
    words = (text or "").encode().translate(LOWER_TABLE).split()
    if not words:
        return 0
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    if len(words) > shingle:
        starts, ends = starts[: len(words) - shingle + 1], ends[shingle - 1 :]
    else:
        starts, ends = starts[:1], ends[-1:]
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(joined[s:e], 42) for s, e in zip(starts.tolist(), ends.tolist(), strict=True)], np.uint64)
    ones = np.zeros(WIDTH, np.int64)
    for k in range(0, len(hashes), 1 << 16):
        part = hashes[k : k + (1 << 16)].astype(">u8").view(np.uint8).reshape(-1, 8)
        ones += np.unpackbits(part, axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > len(hashes)).tobytes(), "big")


def fingerprints(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """(doc_id, fp): fp is the fingerprint's 64 bits as a signed long. One row per row of docs."""

    def run(batches):
        for batch in blocks(batches):
            values = np.array([fingerprint(t, shingle) for t in batch.column(1).to_pylist()], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(values.view(np.int64))], ["doc_id", "fp"])

    return mapped(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), run, "doc_id long, fp long")


class Forest:
    """Labels of leaves under vectorised union."""

    def __init__(self, n: int):
        self.label = np.arange(n)
        self.breaks = np.arange(n + 1)

    def union(self, a: np.ndarray, b: np.ndarray) -> None:
        label = self.label
        while len(a):
            x, y = label[a], label[b]
            apart = x != y
            if not apart.any():
                break
            a, b, x, y = a[apart], b[apart], x[apart], y[apart]
            np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
            while True:
                up = label[label]
                if np.array_equal(up, label):
                    break
                label[:] = up
        self.breaks = np.concatenate(([0, 0], np.cumsum(label[1:] != label[:-1])))[: len(label) + 1] if len(label) else self.breaks

    def one(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """Whether all leaves low..high-1 carry one label."""
        return self.breaks[high] == self.breaks[low + 1]


def trie_links(values: np.ndarray, top: np.ndarray, budget: int) -> tuple[np.ndarray, np.ndarray]:
    """Walks the tries over sorted distinct `values` (uint64), one for each group of equal top bits.

    top: bits that are equal within a group, by group start; returns pairs
    (leaf, smaller leaf) that span the same components as all links do.
    """
    starts, bits = top
    forest = Forest(len(values))
    ends = np.append(starts[1:], len(values))
    many = ends - starts > 1
    stack = [(starts[many], ends[many], starts[many], ends[many], np.full(many.sum(), WIDTH - bits), np.zeros(many.sum(), np.int64))]
    while stack:
        lo1, hi1, lo2, hi2, bit, diff = stack.pop()
        if len(lo1) > FRONTIER:
            stack.append(tuple(x[FRONTIER:] for x in (lo1, hi1, lo2, hi2, bit, diff)))
            lo1, hi1, lo2, hi2, bit, diff = (x[:FRONTIER] for x in (lo1, hi1, lo2, hi2, bit, diff))
        joined = forest.one(lo1, hi1) & forest.one(lo2, hi2) & (forest.label[lo1] == forest.label[lo2])
        leaf = (hi1 - lo1 == 1) & (hi2 - lo2 == 1)
        pair = leaf & ~joined & (lo1 != lo2)
        if pair.any():
            a, b = lo1[pair], lo2[pair]
            near = np.bitwise_count(values[a] ^ values[b]) <= budget
            forest.union(a[near], b[near])
        go = ~leaf & ~joined
        if not go.any():
            continue
        lo1, hi1, lo2, hi2, bit, diff = (x[go] for x in (lo1, hi1, lo2, hi2, bit, diff))
        bit = bit - 1
        mark = np.uint64(1) << bit.astype(np.uint64)
        keep = ~(mark | (mark - np.uint64(1)))
        mid1 = np.clip(np.searchsorted(values, (values[lo1] & keep) | mark), lo1, hi1)
        mid2 = np.clip(np.searchsorted(values, (values[lo2] & keep) | mark), lo2, hi2)
        same = (lo1 == lo2) & (hi1 == hi2)
        child = [(lo1, mid1, lo2, mid2, 0, None), (mid1, hi1, mid2, hi2, 0, None), (lo1, mid1, mid2, hi2, 1, None), (mid1, hi1, lo2, mid2, 1, ~same)]
        parts = []
        for l1, h1, l2, h2, step, only in child:
            ok = (l1 < h1) & (l2 < h2) & (diff + step <= budget) & ~((h1 - l1 == 1) & (l1 == l2))
            if only is not None:
                ok &= only
            parts.append([x[ok] for x in (l1, h1, l2, h2, bit, diff + step)])
        stack.append(tuple(np.concatenate(x) for x in zip(*parts, strict=True)))
    leaf = np.flatnonzero(forest.label != np.arange(len(values)))
    return leaf, forest.label[leaf]


def cuts(low: int, high: int, parts: int) -> list[tuple[int, int]]:
    """Bits low..high-1 in `parts` runs, as (shift, width)."""
    edges = [low + (high - low) * k // parts for k in range(parts + 1)]
    return [(a, b - a) for a, b in zip(edges, edges[1:], strict=False)]


def _bits(column, shift: int, width: int):
    return F.shiftrightunsigned(column, shift).bitwiseAND(F.lit((1 << width) - 1))


def links(points: DataFrame, budget: int, bound: int, scratch: Scratch) -> DataFrame:
    """(u, v) over `rep` of points (fp, rep; fp distinct): a forest that spans all links within the budget."""
    blocks_ = cuts(0, WIDTH, budget + 1)
    dealt = points.select("fp", "rep", F.explode(F.array(*[F.struct(F.lit(k).alias("turn"), _bits(F.col("fp"), *b).alias("key")) for k, b in enumerate(blocks_)])).alias("d")).select("fp", "rep", "d.turn", "d.key")
    # Values of a block that hold too many fingerprints get the blocks of the other bits as a second key.
    hot = dealt.groupBy("turn", "key").count().where(F.col("count") > bound).select("turn", "key")
    hot = scratch.keep(hot)
    if hot.isEmpty():
        keyed = dealt.select("turn", "key", F.lit(0).alias("turn2"), F.lit(0).cast("long").alias("key2"), "fp", "rep")
    else:
        marked = dealt.join(hot.withColumn("hot", F.lit(True)), ["turn", "key"], "left")
        second = []
        for turn, (shift, width) in enumerate(blocks_):
            # the other bits, rotated to the lower end
            spare = F.when(F.lit(shift + width < WIDTH), F.shiftrightunsigned("fp", (shift + width) % WIDTH)).otherwise(F.lit(0).cast("long")).bitwiseOR(F.shiftleft(F.col("fp").bitwiseAND(F.lit((1 << shift) - 1)), WIDTH - shift - width) if shift else F.lit(0).cast("long"))
            pieces = [F.struct(F.lit(k + 1).alias("turn2"), _bits(spare, *b).alias("key2")) for k, b in enumerate(cuts(0, WIDTH - width, budget + 1))]
            second.append(F.when(F.col("turn") == turn, F.array(*pieces)))
        plain = F.array(F.struct(F.lit(0).alias("turn2"), F.lit(0).cast("long").alias("key2")))
        keyed = marked.select("turn", "key", "fp", "rep", F.explode(F.when(F.col("hot"), F.coalesce(*second)).otherwise(plain)).alias("d")).select("turn", "key", "d.turn2", "d.key2", "fp", "rep")

    def run(batches):
        """Subtries come sorted by their keys; whole ones are walked as soon as FRONTIER rows are there."""
        held, n = [], 0
        for batch in batches:
            held.append(batch)
            n += batch.num_rows
            if n >= FRONTIER:
                table = pa.Table.from_batches(held).combine_chunks()
                last = [table.column(k)[-1] for k in range(4)]
                open_ = np.ones(n, bool)
                for k, value in enumerate(last):
                    open_ &= table.column(k).to_numpy() == value.as_py()
                cut = int(np.argmax(open_))
                if cut:
                    yield from walk(table.slice(0, cut))
                    held, n = table.slice(cut).combine_chunks().to_batches(), n - cut
        if n:
            yield from walk(pa.Table.from_batches(held))

    def walk(table):
        table = table.combine_chunks()
        turn, key, turn2, key2, fp, rep = (table.column(k).to_numpy() for k in range(6))
        fp = fp.view(np.uint64)
        for now, (shift, width) in enumerate(blocks_):
            at = np.flatnonzero(turn == now)
            if not len(at):
                continue
            left = (WIDTH - shift - width) % WIDTH
            turned = (fp[at] << np.uint64(left)) | (fp[at] >> np.uint64(WIDTH - left)) if left else fp[at]
            for inner in np.unique(turn2[at]):
                mine = np.flatnonzero(turn2[at] == inner)
                if inner:
                    # within a second key the walk begins below the first block only
                    order = mine[np.lexsort((turned[mine], key2[at][mine]))]
                    group = np.flatnonzero(np.r_[True, np.diff(key2[at][order]) != 0])
                    for a, b in zip(group, np.append(group[1:], len(order)), strict=True):
                        yield from emit(turned[order[a:b]], rep[at][order[a:b]], width)
                else:
                    order = mine[np.argsort(turned[mine])]
                    yield from emit(turned[order], rep[at][order], width)

    def emit(values, rep, width):
        prefix = values >> np.uint64(WIDTH - width)
        starts = np.flatnonzero(np.r_[True, prefix[1:] != prefix[:-1]])
        child, parent = trie_links(values, (starts, width), budget)
        if len(child):
            yield pa.RecordBatch.from_arrays([pa.array(rep[child]), pa.array(rep[parent])], ["u", "v"])

    # as many parts as rows ask for, however few the session's default are
    parts = max(int(points.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-keyed.count() // (4 * FRONTIER)))
    by = ["turn", "key", "turn2", "key2"]
    return mapped(keyed.repartition(parts, *by).sortWithinPartitions(*by), run, "u long, v long")


def simhash_components(docs: DataFrame, budget: int = 2, shingle: int = 3, bound: int = 1 << 18) -> DataFrame:
    """(doc_id, fp, component_id) for every row of docs.

    Documents link if their fingerprints differ in at most `budget` bits;
    component_id is the smallest doc_id reachable. A text that is null, empty
    or without words has fingerprint 0 and links like any other. Repeated rows
    give repeated results; a null doc_id counts as no node and keeps a null
    component. An empty table gives an empty one.
    """
    scratch = Scratch(docs.sparkSession, "simhash")
    marks = scratch.keep(fingerprints(docs, shingle))
    points = scratch.keep(marks.where("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies")))
    roots = components(links(points.select("fp", "rep"), budget, bound, scratch), scratch)
    named = points.join(roots, points.rep == roots.node, "left").select("fp", F.coalesce("root", "rep").alias("component_id"))
    return marks.join(named, "fp", "left").select("doc_id", "fp", F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"))


def simhash_representatives(docs: DataFrame, budget: int = 2) -> DataFrame:
    """docs without all but one document of each component; columns as they came.

    The document with the smallest doc_id stays. Rows without doc_id stay. Of
    rows that share that doc_id the one with the least text stays, then the
    least of the other columns.
    """
    found = simhash_components(docs.select("doc_id", "text"), budget)
    firsts = found.where("doc_id = component_id").select(F.col("doc_id").alias("kept")).distinct()
    kept = docs.join(firsts, docs["doc_id"].cast("long") == firsts["kept"], "left_semi")
    several = kept.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1")
    if not several.isEmpty():
        # the least row by parts: an id may have very many
        rest = [F.col(f"`{c}`") for c in docs.columns if c != "text"]
        least = kept.groupBy("doc_id").agg(F.min(F.struct("text", *rest)).alias("row"))
        kept = least.select(*[F.col(f"row.`{c}`").alias(c) for c in docs.columns])
    return kept.unionByName(docs.where(F.col("doc_id").isNull()))
