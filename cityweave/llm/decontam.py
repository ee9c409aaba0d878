"""Benchmark decontamination by spaced seeds.

A seed is a fixed mask over nine consecutive tokens of which six count and
three may be anything. Seeds of the test items and of the documents are joined
by their hashes; around each match the document and the item are laid on each
other and compared word by word, so that substitutions don't hide a copy.

Documents have far more seeds than items, so the documents' seeds pass a filter
of bounded size before the join: a bit table of the items' seeds, made by a
distributed sum. What it lets through by chance, the join drops.
"""

from __future__ import annotations

import hashlib
import math
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cityweave.llm.kernel import Words, blocks, buffers, mapped, mix, window_hash
from cityweave.scratch import Scratch

# Token positions that count, by mask.
MASKS = ((0, 1, 2, 5, 6, 8), (0, 2, 3, 4, 7, 8), (0, 1, 3, 5, 7, 8), (0, 1, 4, 6, 7, 8))
SPAN = 9
#: Items under so many words have masks of their own, as those above can miss them.
SHORT = 12

# Tokens are runs of ASCII letters, digits and bytes of other scripts.
BETWEEN = np.ones(256, bool)
BETWEEN[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = False

#: Bits of the filter: between these powers of two, SPARSE for each seed within them.
LEAST_BITS, MOST_BITS, SPARSE, PROBES = 20, 28, 32, 4
#: Cells (diagonals x words) that are compared in one go.
CELLS = 1 << 21


def short_masks(size: int, share: float) -> list[tuple[int, ...]]:
    """Masks over all words of a short item, one of which is spared by any substitutions that leave `share` of the words.

    The words are dealt into two groups more than there may be substitutions,
    and each mask leaves out as many groups as there may be substitutions.
    """
    wrong = size - max(math.ceil(share * size - 1e-9), 0)
    groups = min(wrong + 2, size)
    return [tuple(k for k in range(size) if k % groups not in out) for out in combinations(range(groups), wrong)] if wrong else [tuple(range(size))]


def all_masks(sizes: list[int], share: float) -> list[tuple[int, tuple[int, ...]]]:
    """(words, mask) of every kind of seed, for items of which the short ones have the given sizes."""
    return [(SPAN, m) for m in MASKS] + [(n, m) for n in sorted(sizes) for m in short_masks(n, share)]


def _lists(values: np.ndarray, counts: np.ndarray, kind) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(counts))).astype(np.int32)), pa.array(values, kind))


ITEM = "item_id long, words array<long>, seeds array<long>, at array<int>"


def item_table(items: DataFrame, share: float) -> DataFrame:
    """(item_id, words, seeds, at): word hashes of each item, and its seeds with their first words."""

    # short items' masks are numbered as if all short sizes were there
    place = {m: n for n, m in enumerate(all_masks(list(range(1, SHORT)), share))}

    def run(batches):
        for batch in blocks(batches):
            rows = []
            words = Words(*buffers(batch.column(1)), BETWEEN)
            hashes = words.hashes(fold=True)
            for k, item in enumerate(batch.column(0).to_pylist()):
                own = hashes[words.first[k] : words.first[k + 1]]
                masks = all_masks([len(own)] if 0 < len(own) < SHORT else [], share)
                found = [mix(window_hash(own, mask, width) + np.uint64(place[width, mask])) for width, mask in masks]
                if len(own):
                    rows.append((item, own.view(np.int64), np.concatenate(found).view(np.int64), np.concatenate([np.arange(len(f)) for f in found])))
            ids, own, values, at = list(zip(*rows, strict=True)) or [[]] * 4
            flat = lambda parts, kind: _lists(np.concatenate(parts) if len(parts) else np.zeros(0), np.array([len(x) for x in parts], np.int64), kind)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), flat(own, pa.int64()), flat(values, pa.int64()), flat(at, pa.int32())], ["item_id", "words", "seeds", "at"])

    return mapped(items, run, ITEM)


def _probe(hashes: np.ndarray, bits: int, k: int) -> np.ndarray:
    return (hashes if k == 0 else mix(hashes + np.uint64(k))) >> np.uint64(64 - bits)


def seed_filter(table: DataFrame) -> tuple[np.ndarray, int]:
    """A table of 2**bits bits, packed into bytes, with PROBES bits set for each seed of the items. At most 2**MOST_BITS bits."""
    n = table.agg(F.sum(F.size("seeds"))).first()[0] or 0
    bits = min(max(math.ceil(math.log2(SPARSE * n + 1)), LEAST_BITS), MOST_BITS)

    def run(batches):
        for batch in batches:
            flat = np.unique(batch.column(0).flatten().to_numpy(zero_copy_only=False).view(np.uint64))
            places = np.unique(np.concatenate([_probe(flat, bits, k) for k in range(PROBES)])) if len(flat) else flat
            byte = (places >> np.uint64(3)).astype(np.int64)
            value = np.uint64(1) << (places & np.uint64(7))
            yield pa.RecordBatch.from_arrays([pa.array(byte), pa.array(value.astype(np.int64))], ["byte", "value"])

    marks = mapped(table.select("seeds"), run, "byte long, value long").groupBy("byte").agg(F.bit_or("value").alias("value"))
    out = np.zeros(1 << (bits - 3), np.uint8)
    # at most one row for each byte of the table, whatever the items
    found = marks.toPandas()
    out[found["byte"].to_numpy(np.int64)] = found["value"].to_numpy(np.int64).astype(np.uint8)
    return out, bits


HIT = "row long, doc_id long, key string, words array<long>, hits array<long>, at array<int>"


def document_hits(docs: DataFrame, table: np.ndarray, bits: int, sizes: list[int], share: float) -> DataFrame:
    """(row, doc_id, key, words, hits, at) of documents with seeds that pass the filter; key is a digest of the text."""
    every = all_masks(list(range(1, SHORT)), share)
    masks = [(k, m) for k, m in enumerate(every) if k < len(MASKS) or m[0] in sizes]

    def passing(hashes: np.ndarray, words: Words):
        for k, (width, mask) in masks:
            if len(hashes) < width:
                continue
            own = mix(window_hash(hashes, mask, width) + np.uint64(k))
            at = np.flatnonzero(words.doc[: len(own)] == words.doc[width - 1 :])
            for probe in range(PROBES):
                place = _probe(own[at], bits, probe)
                at = at[(table[place >> np.uint64(3)] >> (place & np.uint64(7)).astype(np.uint8)) & 1 > 0]
            yield own[at], at

    def run(batches):
        for batch in blocks(batches):
            data, offsets = buffers(batch.column(2))
            words = Words(data, offsets, BETWEEN)
            hashes = words.hashes(fold=True)
            found = list(passing(hashes, words))
            if not sum(len(at) for _, at in found):
                continue
            value, at = (np.concatenate(x) for x in zip(*found, strict=True))
            doc = words.doc[at]
            order = np.argsort(doc, kind="stable")
            value, at, doc = value[order], at[order], doc[order]
            own, counts = np.unique(doc, return_counts=True)
            text = [hashlib.sha256(data[offsets[d] : offsets[d + 1]].tobytes()).hexdigest() for d in own.tolist()]
            flat = np.concatenate([hashes[words.first[d] : words.first[d + 1]] for d in own.tolist()])
            cols = [batch.column(0).take(pa.array(own)), batch.column(1).take(pa.array(own)), pa.array(text), _lists(flat.view(np.int64), words.count[own], pa.int64()), _lists(value.view(np.int64), counts, pa.int64()), _lists((at - words.first[doc]).astype(np.int32), counts, pa.int32())]
            yield pa.RecordBatch.from_arrays(cols, ["row", "doc_id", "key", "words", "hits", "at"])

    return mapped(docs, run, HIT)


def diagonals(hits: np.ndarray, at: np.ndarray, item_seeds: np.ndarray, item_at: np.ndarray, n_doc: int, n_item: int) -> np.ndarray:
    """Distinct starts of an item in a document's words at which a seed of both agrees.

    Places of a seed that repeats on both sides are not paired one by one: the
    document's places are a bit string, shifted once for each place in the item.
    """
    out = []
    order = np.argsort(hits, kind="stable")
    keys, places = hits[order], at[order]
    own = np.argsort(item_seeds, kind="stable")
    values, first = np.unique(item_seeds[own], return_index=True)
    low, high = np.searchsorted(keys, values, "left"), np.searchsorted(keys, values, "right")
    ends = np.append(first[1:], len(own))
    seen: set[bytes] = set()
    for k in np.flatnonzero(high > low).tolist():
        theirs, mine = places[low[k] : high[k]], item_at[own[first[k] : ends[k]]]
        if len(theirs) * len(mine) <= 1 << 12:
            out.append((theirs[:, None] - mine[None, :]).ravel())
            continue
        # masks of one run of equal words have the same places
        name = hashlib.sha256(theirs.tobytes() + b"|" + mine.tobytes()).digest()
        if name in seen:
            continue
        seen.add(name)
        marks = np.zeros(n_doc, np.uint8)
        marks[theirs] = 1
        line = int.from_bytes(np.packbits(marks, bitorder="little").tobytes(), "little")
        total = 0
        for b in mine.tolist():
            total |= line << (n_item - b)
        found = np.unpackbits(np.frombuffer(total.to_bytes((total.bit_length() + 7) // 8, "little"), np.uint8), bitorder="little")
        out.append(np.flatnonzero(found) - n_item)
    return np.unique(np.concatenate(out)) if out else np.zeros(0, np.int64)


def overlaps(doc: np.ndarray, item: np.ndarray, starts: np.ndarray, span: int, share: float) -> list[tuple[int, int, int]]:
    """(first word, words, agreeing words) of maximal runs of a document's words covered by windows that agree with the item."""
    n, m, size = len(doc), len(item), min(span, len(item))
    if n < size:
        return []
    covered, agreeing = np.zeros(n + 1, np.int64), np.zeros(n, bool)
    column = np.arange(m)
    step = max(1, CELLS // max(m, 1))
    for k in range(0, len(starts), step):
        begin = starts[k : k + step, None]
        at = begin + column
        inside = (at >= 0) & (at < n)
        same = inside & (doc[np.clip(at, 0, n - 1)] == item)
        sums = np.zeros((len(same), m + 1), np.int32)
        np.cumsum(same, axis=1, out=sums[:, 1:])
        good = (sums[:, size:] - sums[:, :-size] >= share * size - 1e-9) & inside[:, : m - size + 1] & inside[:, size - 1 :]
        some = good.any(axis=1)
        if not some.any():
            continue
        good, same, at = good[some], same[some], at[some]
        row, first = np.nonzero(good)
        place = at[row, first]
        covered += np.bincount(place, minlength=n + 1) - np.bincount(place + size, minlength=n + 1)
        # words under a good window
        under = np.zeros((len(good), m + 1), np.int32)
        np.add.at(under, (row, first), 1)
        np.add.at(under, (row, first + size), -1)
        told = same & (np.cumsum(under[:, :-1], axis=1) > 0)
        agreeing[at[told]] = True
    on = np.concatenate(([False], np.cumsum(covered[:-1]) > 0, [False]))
    low, high = np.flatnonzero(on[1:] & ~on[:-1]), np.flatnonzero(~on[1:] & on[:-1])
    total = np.concatenate(([0], np.cumsum(agreeing)))
    return [(a, b - a, int(total[b] - total[a])) for a, b in zip(low.tolist(), high.tolist(), strict=True)]


FOUND = "doc_id long, key string, item_id long, first_word long, n_words long, n_same long"


def _verified(joined: DataFrame, span: int, share: float) -> DataFrame:
    def run(batches):
        for batch in batches:
            rows = []
            column = {n: batch.column(k) for k, n in enumerate(batch.schema.names)}
            array = lambda value: value.values.to_numpy(zero_copy_only=False)
            for k in range(batch.num_rows):
                doc, hits, at = (array(column[n][k]) for n in ("words", "hits", "at"))
                for item in column["items"][k].values:
                    own, found, where = (array(item[n]) for n in ("words", "seeds", "at"))
                    starts = diagonals(hits, at.astype(np.int64), found, where.astype(np.int64), len(doc), len(own))
                    rows += [(column["doc_id"][k].as_py(), column["key"][k].as_py(), item["item_id"].as_py(), *r) for r in overlaps(doc, own, starts, span, share)]
            cols = list(zip(*rows, strict=True)) or [[]] * 6
            kinds = (pa.int64(), pa.string(), *[pa.int64()] * 4)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], ["doc_id", "key", "item_id", "first_word", "n_words", "n_same"])

    return mapped(joined.select("doc_id", "key", "words", "hits", "at", "items"), run, FOUND)


def _overlaps(docs: DataFrame, items: DataFrame, span: int, share: float) -> DataFrame:
    """FOUND rows of docs (doc_id, text)."""
    scratch = Scratch(docs.sparkSession, "decontam")
    chosen = items.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where("item_id is not null and text is not null").distinct()
    table = scratch.keep(item_table(chosen, share).withColumn("ikey", F.monotonically_increasing_id()))
    sizes = [r[0] for r in table.select(F.size("words")).where(F.size("words") < SHORT).distinct().collect()]
    bits, width = seed_filter(table)
    rows = docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    hits = scratch.keep(document_hits(rows, bits, width, sizes, share))
    theirs = table.select("ikey", F.explode(F.array_distinct("seeds")).alias("seed"))
    pairs = hits.select("row", F.explode(F.array_distinct("hits")).alias("seed")).join(theirs, "seed").select("row", "ikey").distinct()
    # the items that one document may hold, not the documents of an item, come together
    grouped = pairs.join(table, "ikey").groupBy("row").agg(F.collect_list(F.struct("item_id", "words", "seeds", "at")).alias("items"))
    return _verified(hits.join(grouped, "row"), span, share)


def contamination(docs: DataFrame, items: DataFrame, span: int = 13, share: float = 0.8) -> DataFrame:
    """(doc_id, item_id, first_word, n_words, n_same) for every overlap of a document with a test item.

    A window of `span` words (all of the item, if it is shorter) overlaps if the
    document and the item, laid on each other, agree on at least `share` of
    them. A row is a maximal run of the document's words under such windows,
    whichever way the item lies, n_same the words of it that agree in one of
    them. Null or empty texts overlap with nothing; repeated rows of docs give
    repeated results, repeated items don't; rows without item_id are left out.
    """
    return _overlaps(docs, items, span, share).drop("key")


def drop_contaminated(docs: DataFrame, items: DataFrame, span: int = 13, share: float = 0.8) -> DataFrame:
    """docs, in its own columns, without those that overlap with a test item. Whether one does depends on its text alone."""
    found = _overlaps(docs.select("doc_id", "text"), items, span, share).select(F.col("key").alias("key")).distinct()
    found = Scratch(docs.sparkSession, "decontam").keep(found)
    return docs.join(found, F.sha2(docs["text"].cast("string"), 256) == found["key"], "left_anti")
