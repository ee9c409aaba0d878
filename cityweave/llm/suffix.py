"""Exact removal of repeated byte strings by distributed suffix sorting.

A byte goes if it lies in a string of SIZE bytes that also starts earlier.
Equal strings of that size have equal content anchors: the gram with the least
hash among those inside the string. So strings are dealt out by anchor, each
to one group, and all places of a string meet there:

1. Every document is cut into runs of neighbouring strings with one anchor. A
   run is known by its anchor and a hash of its text.
2. Runs whose anchor comes once in the corpus can't repeat and end here. Of
   equal runs all but the first are repeats throughout.
3. What is left are anchors with several different texts around them. Their
   texts are fetched, dealt by anchor, and sorted: the suffixes at two of three
   positions by the names of their triples, recursively; the others by merging.
   Suffixes that are neighbours in that order and agree on SIZE bytes are the
   same string; all but the first place are repeats.

An anchor with more than `hot` texts is dealt by further anchors of its
strings, from other hash functions. A part of those that still has more than
LARGE bytes, as when one line of 70 to 99 bytes stands in very many documents,
isn't sorted in one task: its strings go through the cluster one by one, and
equal ones are brought together by their bytes.
"""

from __future__ import annotations

import hashlib
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cityweave.llm.kernel import blocks, buffers, mapped, mix, prefix_hash, span_hash
from cityweave.scratch import Scratch, free_shuffles

SIZE = 100
GRAM = 24
GRAMS = SIZE - GRAM + 1
#: Bytes of window starts that are looked at in one go; positions must fit in 24 bits.
SEGMENT = 4 << 20
#: Characters that one suffix sort takes at least, if there are as many; a part is never cut.
SORTED = 1 << 19
#: Bytes of a part that one task sorts at most.
LARGE = 4 << 20
#: Names of triples of triples ... that cover SIZE characters.
DEPTH = 5


def sliding_least(values: np.ndarray, width: int) -> np.ndarray:
    """Least value in each run of `width` neighbours."""
    have, out = 1, values
    while 2 * have <= width:
        out = np.minimum(out[: len(out) - have], out[have:])
        have *= 2
    rest = width - have
    return np.minimum(out[: len(out) - rest], out[rest:]) if rest else out


def anchors(grams: np.ndarray, salt: int = 0) -> np.ndarray:
    """Position of the gram with the least hash (the first of several) in each window of GRAMS grams."""
    h = mix(grams + np.uint64(salt * 0x9E3779B9 + 1))
    at = np.arange(len(h), dtype=np.uint64)
    return (sliding_least((h & np.uint64(0xFFFFFFFFFF000000)) | at, GRAMS) & np.uint64(0xFFFFFF)).astype(np.int64)


def runs(data: np.ndarray, offsets: np.ndarray):
    """(document, first string, strings, anchor, text hash) of each run of strings with one anchor."""
    if len(data) < SIZE:
        return
    prefix = prefix_hash(data)
    at = np.arange(len(data) - GRAM + 1)
    grams = mix(span_hash(prefix, at, at + GRAM))
    where = anchors(grams)
    doc = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    whole = doc[: len(where)] == doc[SIZE - 1 :]
    cut = np.ones(len(where), bool)
    cut[1:] = (where[1:] != where[:-1]) | (doc[1 : len(where)] != doc[: len(where) - 1])
    lo = np.flatnonzero(cut & whole)
    if not len(lo):
        return
    # a run ends where the next begins, or where strings of its document end
    last = offsets[doc[lo] + 1] - SIZE + 1
    n = np.minimum(np.append(lo[1:], len(where)), last) - lo
    yield doc[lo], lo, n, grams[where[lo]], mix(span_hash(prefix, lo, lo + n + SIZE - 1) + n.astype(np.uint64))


def segments(batches, text: str = "text"):
    """(row ids, data, offsets, first string) of blocks of text, long documents in overlapping parts."""
    for batch in blocks(batches, text):
        ids = batch.column(0).to_numpy(zero_copy_only=False)
        data, offsets = buffers(batch.column(batch.schema.get_field_index(text)))
        if len(data) <= SEGMENT:
            yield ids, data, offsets, 0
            continue
        for row in range(len(ids)):
            a, b = int(offsets[row]), int(offsets[row + 1])
            for at in range(a, max(b, a + 1), SEGMENT):
                part = data[at : min(at + SEGMENT + SIZE - 1, b)]
                yield ids[row : row + 1], part, np.array([0, len(part)]), at - a


RUN = "key long, ctx long, doc_id long, lo long, n int, later boolean"


def all_runs(docs: DataFrame) -> DataFrame:
    """Runs of all documents; `later` marks those that a run of the same block precedes with the same text."""

    def run(batches):
        for ids, data, offsets, first in segments(batches):
            for doc, lo, n, key, ctx in runs(data, offsets):
                same = mix(key ^ mix(ctx))
                owner, start = ids[doc], lo - offsets[doc] + first
                order = np.lexsort((start, owner, same))
                later = np.zeros(len(order), bool)
                later[order[1:]] = (same[order][1:] == same[order][:-1]) & (ctx[order][1:] == ctx[order][:-1])
                cols = [key.view(np.int64), ctx.view(np.int64), owner, start, n.astype(np.int32), later]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], ["key", "ctx", "doc_id", "lo", "n", "later"])

    return mapped(docs, run, RUN)


def _rank(keys: np.ndarray) -> tuple[np.ndarray, int]:
    """Names 1.. of keys in their order, and how many there are."""
    order = np.argsort(keys)
    new = np.ones(len(keys), np.int64)
    new[1:] = keys[order][1:] != keys[order][:-1]
    names = np.empty(len(keys), np.int64)
    names[order] = np.cumsum(new)
    return names, int(new.sum())


def suffix_order(s: np.ndarray, level: int = 0) -> np.ndarray:
    """Suffixes of s (symbols from 1) in order of at least their first 3**DEPTH symbols.

    The difference cover modulo 3 takes positions 1 and 2: their triples are
    named by rank and the names sorted as a string of their own, until names
    differ or reach deep enough. Positions 0 are sorted by their symbol and the
    rank behind it, and merged by two searches among the others.
    """
    n = len(s)
    if n < 3:
        return np.array(sorted(range(n), key=lambda i: s[i:].tolist()), np.int64)
    t = np.concatenate((s, [0, 0, 0])).astype(np.int64)
    bits = int(t.max()).bit_length()
    # with n % 3 == 1 an empty suffix at n keeps the two classes apart in the reduced string
    one, two = np.arange(1, n + (n % 3 == 1), 3), np.arange(2, n, 3)
    sample = np.concatenate((one, two))
    pair = (t[:-1] << bits) | t[1:]
    if 3 * bits > 62:  # very long strings: pairs are named first
        pair = _rank(pair)[0]
    wide = int(pair.max()).bit_length()
    names, distinct = _rank((pair[sample] << bits) | t[sample + 2])
    if distinct < len(sample) and level + 1 < DEPTH:
        below = suffix_order(names, level + 1)
    else:
        below = np.argsort(names, kind="stable")
    ordered = sample[below]
    rank = np.zeros(n + 3, np.int64)
    rank[ordered] = np.arange(1, len(ordered) + 1)
    zero = np.arange(0, n, 3)
    width = int(len(ordered) + 1).bit_length()
    zero_key = (t[zero] << width) | rank[zero + 1]
    by = np.argsort(zero_key)
    zero, zero_key = zero[by], zero_key[by]
    first, second = ordered[ordered % 3 == 1], ordered[ordered % 3 == 2]
    before = np.searchsorted((t[first] << width) | rank[first + 1], zero_key)
    if wide + width > 62:
        pair = _rank(pair)[0]
    before = before + np.searchsorted((pair[second] << width) | rank[second + 2], (pair[zero] << width) | rank[zero + 2])
    place = np.maximum.accumulate(before) + np.arange(len(zero))
    out = np.empty(len(zero) + len(ordered), np.int64)
    taken = np.zeros(len(out), bool)
    taken[place] = True
    out[place] = zero
    out[~taken] = ordered
    return out[out < n]


def repeated_starts(text: np.ndarray, own: np.ndarray) -> np.ndarray:
    """Those of the positions `own` (ascending) whose SIZE bytes also start at an earlier one of them."""
    is_own = np.zeros(len(text), bool)
    is_own[own] = True
    order = suffix_order(text.astype(np.int64) + 1)
    order = order[is_own[order]]
    same = np.zeros(len(order), bool)
    views = np.lib.stride_tricks.sliding_window_view(text, SIZE)
    for k in range(1, len(order), 1 << 15):
        a, b = order[k - 1 : k - 1 + (1 << 15)], order[k : k + (1 << 15)]
        same[k : k + len(b)] = (views[a[: len(b)]] == views[b]).all(axis=1)
    heads = np.flatnonzero(~same)
    if not len(heads):
        return order[:0]
    earliest = np.repeat(np.minimum.reduceat(order, heads), np.diff(np.append(heads, len(order))))
    return order[order != earliest]


CONTEXT = "part long, doc_id long, lo long, n int, text binary"


def contexts(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """Texts of the wanted runs (doc_id, key, lo, n, hot); hot ones cut further by other anchors."""
    lists = wanted.groupBy("doc_id").agg(F.collect_list(F.struct("key", "lo", "n", "hot")).alias("runs"))

    def cut(data: np.ndarray, key: int, lo: int, n: int):
        text = data[lo : lo + n + SIZE - 1]
        prefix, at = prefix_hash(text), np.arange(len(text) - GRAM + 1)
        grams = mix(span_hash(prefix, at, at + GRAM))
        part = np.full(n, key, np.int64).view(np.uint64)
        for salt in (1, 2, 3):
            part = mix(part ^ grams[anchors(grams, salt)])
        starts = np.flatnonzero(np.r_[True, part[1:] != part[:-1]])
        for a, b in zip(starts.tolist(), np.append(starts[1:], n).tolist(), strict=True):
            yield int(part[a : a + 1].view(np.int64)[0]), lo + a, b - a

    def run(batches):
        for batch in blocks(batches):
            out = []
            for doc, text, own in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist(), strict=True):
                raw = text.as_buffer()
                data = np.frombuffer(raw, np.uint8)
                for r in own:
                    parts = cut(data, r["key"], r["lo"], r["n"]) if r["hot"] else ((r["key"], r["lo"], r["n"]),)
                    out += [(k, doc, lo, n, data[lo : lo + n + SIZE - 1].tobytes()) for k, lo, n in parts]
            cols = list(zip(*out, strict=True)) or [[]] * 5
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["part", "doc_id", "lo", "n", "text"])

    return mapped(docs.join(lists, "doc_id").select("doc_id", "text", "runs"), run, CONTEXT)


def sorted_repeats(texts: DataFrame) -> DataFrame:
    """(doc_id, lo, hi): byte ranges that are repeats, from the suffix order of each part's texts."""

    def settle(rows: list):
        rows.sort(key=lambda r: (r[1], r[2]))
        text = np.frombuffer(b"".join(r[4] for r in rows), np.uint8)
        sizes = np.array([len(r[4]) for r in rows])
        begin = np.cumsum(sizes) - sizes
        n = np.array([r[3] for r in rows])
        which = np.repeat(np.arange(len(rows)), n)
        own = begin[which] + np.arange(len(which)) - np.repeat(np.cumsum(n) - n, n)
        again = np.sort(repeated_starts(text, own))
        if not len(again):
            return None
        row = np.searchsorted(begin, again, "right") - 1
        head = np.flatnonzero(np.r_[True, (np.diff(again) != 1) | (np.diff(row) != 0)])
        tail = np.append(head[1:], len(again)) - 1
        doc, lo = np.array([r[1] for r in rows])[row[head]], np.array([r[2] for r in rows])[row[head]]
        lo = lo + again[head] - begin[row[head]]
        return pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(lo, pa.int64()), pa.array(lo + again[tail] - again[head] + SIZE, pa.int64())], ["doc_id", "lo", "hi"])

    def run(batches):
        held, size, part = [], 0, None
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if row[0] != part and size >= SORTED:
                    if (out := settle(held)) is not None:
                        yield out
                    held, size = [], 0
                part = row[0]
                held.append(row)
                size += len(row[4])
        if held and (out := settle(held)) is not None:
            yield out

    return mapped(texts.repartition("part").sortWithinPartitions("part"), run, "doc_id long, lo long, hi long")


def spread_repeats(texts: DataFrame) -> DataFrame:
    """The same as sorted_repeats for parts of any size: a row for each string, equal strings by their bytes.

    The least place of a string comes from partial sums, so a string that comes
    very often stays in no one task.
    """

    def run(batches):
        for batch in batches:
            for _, doc, lo, n, text in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                data = np.frombuffer(text, np.uint8)
                flat = np.ascontiguousarray(np.lib.stride_tricks.sliding_window_view(data, SIZE))
                ends = pa.py_buffer((np.arange(n + 1) * SIZE).astype(np.int32))
                strings = pa.BinaryArray.from_buffers(pa.binary(), n, [None, ends, pa.py_buffer(flat)])
                yield pa.RecordBatch.from_arrays([strings, pa.array(np.full(n, doc)), pa.array(np.arange(lo, lo + n))], ["string", "doc_id", "lo"])

    strings = mapped(texts, run, "string binary, doc_id long, lo long")
    first = strings.groupBy("string").agg(F.min(F.struct("doc_id", "lo")).alias("first"), F.count("*").alias("c")).where("c > 1").drop("c")
    again = strings.join(first, "string").where(F.struct("doc_id", "lo") != F.col("first"))
    return again.select("doc_id", "lo", (F.col("lo") + SIZE).alias("hi"))


REPORT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def remaining(text: bytes, ranges: list[tuple[int, int]]) -> tuple[bytes, int]:
    """What is left of a text without the ranges, and the number of maximal runs removed."""
    kept, at, spans = [], 0, 0
    end = None
    for lo, hi in sorted(ranges):
        if end is None or lo > end:
            kept.append(text[at if end is None else end : lo])
            spans += 1
            end = hi
        else:
            end = max(end, hi)
    kept.append(text[0 if end is None else end :])
    return b"".join(kept), spans


def removed_ranges(docs: DataFrame, scratch: Scratch, hot: int = 2000, large: int = LARGE) -> DataFrame:
    """(doc_id, lo, hi) of byte ranges covered by repeated strings; ranges may overlap. docs: (doc_id, text)."""
    spark = docs.sparkSession
    found = scratch.keep(all_runs(docs))
    first = found.where("not later")
    again = first.groupBy("key").agg(F.count("*").alias("c")).where("c > 1").select("key")
    shared = scratch.keep(first.join(again, "key").select("key", "ctx", "doc_id", "lo", "n"))
    ranges = [scratch.keep(found.where("later").select("doc_id", "lo", (F.col("lo") + F.col("n") + SIZE - 1).alias("hi")))]
    scratch.remove(found)
    del found, first, again
    free_shuffles(spark)
    texts = scratch.keep(shared.groupBy("key", "ctx").agg(F.min(F.struct("doc_id", "lo")).alias("first"), F.first("n").alias("n")))
    copies = shared.join(texts.select("key", "ctx", "first"), ["key", "ctx"]).where(F.struct("doc_id", "lo") != F.col("first"))
    ranges.append(scratch.keep(copies.select("doc_id", "lo", (F.col("lo") + F.col("n") + SIZE - 1).alias("hi"))))
    several = texts.groupBy("key").agg(F.count("*").alias("c")).where("c > 1")
    wanted = texts.join(several, "key").select(F.col("first.doc_id").alias("doc_id"), "key", F.col("first.lo").alias("lo"), "n", (F.col("c") > hot).alias("hot"))
    ranges.append(scratch.keep(sorted_repeats(contexts(docs, wanted.where("not hot")))))
    crowded = wanted.where("hot")
    if not crowded.isEmpty():
        parts = scratch.keep(contexts(docs, crowded))
        big = scratch.keep(parts.groupBy("part").agg(F.sum(F.length("text")).alias("size")).where(F.col("size") > large).select("part"))
        ranges.append(scratch.keep(sorted_repeats(parts.join(big, "part", "left_anti"))))
        if not big.isEmpty():
            ranges.append(scratch.keep(spread_repeats(parts.join(big, "part", "left_semi"))))
        scratch.remove(parts)
    scratch.remove(shared)
    scratch.remove(texts)
    del shared, texts, copies, several, wanted, crowded
    free_shuffles(spark)
    return reduce(DataFrame.unionByName, ranges)


def _merged(ranges: DataFrame) -> DataFrame:
    """One list of ranges for each document."""
    return ranges.groupBy("doc_id").agg(F.collect_list(F.struct("lo", "hi")).alias("ranges"))


def without_repeats(docs: DataFrame, hot: int = 2000, large: int = LARGE) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256) for each document.

    Bytes of whole texts (null: empty) are removed where a string of SIZE bytes
    covers them that also starts earlier: in a document with a smaller doc_id,
    or earlier in the same one. Rows that share a doc_id count as one document,
    by the least text; rows without doc_id are left out. Texts shorter than SIZE
    lose nothing; an empty table gives an empty one.
    """
    scratch = Scratch(docs.sparkSession, "suffix")
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).where("doc_id is not null")
    if not plain.groupBy("doc_id").count().where("count > 1").isEmpty():
        plain = plain.groupBy("doc_id").agg(F.min("text").alias("text"))
    lists = _merged(removed_ranges(plain, scratch, hot, large))

    def run(batches):
        for batch in blocks(batches):
            rows = []
            for doc, text, ranges in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist(), strict=True):
                raw = text.as_buffer().to_pybytes()
                left, spans = remaining(raw, [(r["lo"], r["hi"]) for r in ranges or ()])
                rows.append((doc, len(raw), len(raw) - len(left), spans, hashlib.sha256(left).hexdigest()))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], REPORT.replace(" long", "").replace(" string", "").split(", "))

    return mapped(plain.join(lists, "doc_id", "left").select("doc_id", "text", "ranges"), run, REPORT)
