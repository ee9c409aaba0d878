"""Best-fit packing of tokenised documents with certified bin counts.

Documents become pieces of at most `capacity` tokens. Pieces are dealt into
groups of bounded size, each packed by best-fit decreasing. A lower bound from
dual-feasible functions tells for each group how many bins any packing needs;
groups that use more give up their emptiest bins, whose pieces are dealt
together anew and packed again, as long as that saves bins.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from functools import cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cityweave.llm.kernel import blocks, mapped
from cityweave.scratch import Scratch

#: Distinct runs and chunks whose ids a worker remembers.
MEMORY = 400_000

# Plain text is Latin letters, punctuation without apostrophes, and ASCII white
# space. Its tokens before merging are runs of letters and runs of punctuation.
LETTERS, MARKS = r"A-Za-z\u00C0-\u00D6\u00D8-\u00F6\u00F8-\u00FF", r"!-&(-/:-@\[-`{-~"
PLAIN = re.compile(rf"[{LETTERS}{MARKS}\t-\r ]*")
RUNS = re.compile(rf"[{LETTERS}]+|[{MARKS}]+")
#: A string that the tokenizer takes out of a text before all else.
SPECIAL = "<|"


class ChunkTokenizer:
    """Token ids of whole texts, from remembered ids of their runs.

    Only right for tokenizers whose ids don't reach over white space, whose
    normaliser composes and lower-cases characters, and whose pre-tokeniser
    parts letters from punctuation and drops white space. New runs of plain
    texts go through the tokenizer's own model many at a time; its tokens that
    end a word tell where the next one begins. In other texts that holds chunk by
    chunk, between ASCII white space; chunks that aren't plain go through the
    tokenizer as they are.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer, normalizers, pre_tokenizers

        self.whole = Tokenizer.from_file(path)
        self.runs = Tokenizer.from_file(path)
        self.runs.normalizer = normalizers.NFC()
        self.runs.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        vocabulary = self.whole.get_vocab()
        self.ends = np.zeros(max(vocabulary.values()) + 1, bool)
        self.ends[[k for token, k in vocabulary.items() if token.endswith("</w>")]] = True
        #: runs are text here, chunks bytes
        self.known: dict[str | bytes, bytes] = {}

    def _whole(self, text: str) -> bytes:
        return np.array(self.whole.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def _learn(self, runs: list[str]) -> None:
        for k in range(0, len(runs), 4096):
            part = runs[k : k + 4096]
            ids = np.array(self.runs.encode(" ".join(part), add_special_tokens=False).ids, "<u4")
            stops = np.flatnonzero(self.ends[ids]) + 1
            if len(stops) == len(part):
                packed, stops = ids.tobytes(), (4 * stops).tolist()
                self.known.update(zip(part, [packed[a:b] for a, b in zip([0, *stops], stops, strict=False)], strict=True))
            else:
                self.known.update((run, self._whole(run)) for run in part)

    @staticmethod
    def _parts(text: str | None) -> list[str | bytes]:
        if PLAIN.fullmatch(text or "") and SPECIAL not in (text or ""):
            return RUNS.findall((text or "").lower())
        out: list[str | bytes] = []
        for chunk in text.encode().split():
            piece = chunk.decode()
            if PLAIN.fullmatch(piece) and SPECIAL not in piece:
                out += RUNS.findall(piece.lower())
            else:
                out.append(chunk)
        return out

    def ids(self, texts: list[str | None]) -> Iterator[bytes]:
        """Little-endian unsigned 32-bit ids of each text."""
        parts = [self._parts(t) for t in texts]
        if len(self.known) > MEMORY:
            self.known = {}
        new = set().union(*parts).difference(self.known)
        self._learn([x for x in new if isinstance(x, str)])
        for chunk in new:
            if isinstance(chunk, bytes):
                self.known[chunk] = self._whole(chunk.decode())
        for own in parts:
            yield b"".join(map(self.known.__getitem__, own))


@cache
def chunk_tokenizer(path: str) -> ChunkTokenizer:
    """One for each worker process: what it remembers serves the next tasks too."""
    return ChunkTokenizer(path)


def pieces(docs: DataFrame, tokenizer_path: str, capacity: int = 4096, end_id: int = 1) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32): a document's ids and end_id, cut where they exceed capacity.

    Null text counts as empty, that is, end_id alone.
    """
    end = np.array([end_id], "<u4").tobytes()
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long"

    def run(batches):
        own = chunk_tokenizer(tokenizer_path)
        for batch in blocks(batches):
            rows = []
            for doc, ids in zip(batch.column(0).to_pylist(), own.ids(batch.column(1).to_pylist()), strict=True):
                ids += end
                for piece, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    rows.append((doc, piece, at // 4, len(part) // 4, zlib.crc32(part)))
            cols = list(zip(*rows, strict=True))
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return mapped(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), run, schema)


def lower_bound(lengths: np.ndarray, capacity: int) -> int:
    """Bins that any packing of pieces of these lengths needs."""
    return bound_of_counts(np.bincount(lengths, minlength=capacity + 1).astype(np.int64), capacity)


def bound_of_counts(count: np.ndarray, capacity: int) -> int:
    """Bins that any packing needs, by the number of pieces of each length: the best of two families of dual-feasible functions."""
    if not count.any():
        return 0
    size = np.arange(capacity + 1)
    n, mass = np.cumsum(count), np.cumsum(count * size)
    best = -(-int(mass[-1]) // capacity)
    # over capacity - a counts whole, under a not at all, the rest by size
    a = np.arange(1, capacity // 2 + 1)
    whole = n[-1] - n[capacity - a]
    middle = mass[capacity - a] - mass[a - 1]
    best = max(best, int((whole + -(-middle // capacity)).max()))
    # rounding to k-ths
    for k in range(1, 101):
        exact = size * (k + 1) % capacity == 0
        value = np.where(exact, size * k, (size * (k + 1) // capacity) * capacity)  # in k * capacity-ths
        best = max(best, -(-int((value * count).sum()) // (k * capacity)))
    return best


def best_fit_decreasing(lengths: np.ndarray, capacity: int) -> tuple[np.ndarray, np.ndarray]:
    """Bin and offset of each length: longest first, each into the fullest bin that takes it."""
    order = np.argsort(-lengths, kind="stable")
    where, offset = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64)
    by_room: list[list[int]] = [[] for _ in range(capacity + 1)]
    # bit r of `rooms` is set while some open bin has r free tokens
    rooms, used = 0, 0
    for k, size in zip(order.tolist(), lengths[order].tolist(), strict=True):
        fitting = rooms >> size
        if fitting:
            room = size + (fitting & -fitting).bit_length() - 1
            bin_ = by_room[room].pop()
            if not by_room[room]:
                rooms ^= 1 << room
        else:
            room, bin_, used = capacity, used, used + 1
        where[k], offset[k] = bin_, capacity - room
        if left := room - size:
            if not by_room[left]:
                rooms |= 1 << left
            by_room[left].append(bin_)
    return where, offset


def _packer(capacity: int, turn: int):
    def pack(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["length", "doc_id", "piece", "start"], ascending=[False, True, True, True], kind="stable")
        lengths = frame["length"].to_numpy()
        where, offset = best_fit_decreasing(lengths, capacity)
        fill = np.bincount(where, weights=lengths).astype(np.int64)
        gap = len(fill) - lower_bound(lengths, capacity)
        released = np.zeros(len(fill), bool)
        if gap > 0:
            # the emptiest bins, until what they leave free would fill the gap twice over
            emptiest = np.argsort(fill, kind="stable")
            free = np.cumsum(capacity - fill[emptiest])
            released[emptiest[: int(np.searchsorted(free, 2 * (gap + 1) * capacity)) + 1]] = True
        # the bin that is filled least always takes part: another group may have room
        released[fill.argmin()] |= fill.min() < capacity
        group = int(frame["group"].iloc[0])
        out = frame[["doc_id", "piece", "start", "length", "ids_crc32"]].copy()
        out["sequence_id"] = (turn << 60) + (group << 32) + where
        out["offset"] = offset
        out["released"] = released[where]
        out["gap"] = gap
        return out

    return pack


PACKED = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long, released boolean, gap long"
COLUMNS = ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]


def _pack(rows: DataFrame, group_rows: int, capacity: int, turn: int, n: int) -> DataFrame:
    groups = max(1, -(-n // group_rows))
    dealt = rows.withColumn("group", F.pmod(F.xxhash64("doc_id", "piece", F.lit(turn)), F.lit(groups)))
    return dealt.groupBy("group").applyInPandas(_packer(capacity, turn), PACKED)


def best_fit_packing(docs: DataFrame, tokenizer_path: str, capacity: int = 4096, end_id: int = 1, group_rows: int = 200_000, turns: int = 3) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32, sequence_id, offset, n_sequences, lower_bound) for each piece of docs.

    n_sequences is the number of sequences in all, lower_bound what any packing
    of all the pieces needs by the dual-feasible functions: their difference
    bounds what a better packing could save.

    Pieces of one sequence_id lie one after another from offset 0 and have at
    most `capacity` tokens together. Groups of about group_rows pieces are packed
    on their own; up to `turns` exchanges follow. Null text is end_id alone;
    repeated rows are packed as often as they come; an empty table gives none.
    """
    scratch = Scratch(docs.sparkSession, "packing")
    rows = scratch.keep(pieces(docs, tokenizer_path, capacity, end_id))
    whole = rows.where(F.col("length") == capacity)
    rest = rows.where(F.col("length") < capacity)
    # a full piece is a sequence of its own; its number needs only to be unique
    done = [whole.withColumn("sequence_id", F.monotonically_increasing_id() + F.lit(7 << 60)).withColumn("offset", F.lit(0).cast("long"))]
    n = rest.count()
    packed = scratch.keep(_pack(rest, group_rows, capacity, 0, n))
    for turn in range(1, turns + 1):
        loose = packed.where("released")
        n, bins = loose.agg(F.count("*"), F.count_distinct("sequence_id")).first()
        if bins < 2:
            break
        again = scratch.keep(_pack(loose.drop("sequence_id", "offset", "released", "gap"), group_rows, capacity, turn, n))
        if again.select("sequence_id").distinct().count() >= bins:
            break
        done.append(packed.where("not released").select(COLUMNS))
        packed = again
    done.append(packed.select(COLUMNS))
    out = done[0].select(COLUMNS)
    for part in done[1:]:
        out = out.unionByName(part)
    # pieces by length: at most `capacity` rows, whatever the input
    counts = np.zeros(capacity + 1, np.int64)
    for length, count in rows.groupBy("length").count().collect():
        counts[length] = count
    used = whole.count() + sum(part.agg(F.count_distinct("sequence_id")).first()[0] for part in done[1:])
    return out.withColumns({"n_sequences": F.lit(used).cast("long"), "lower_bound": F.lit(bound_of_counts(counts, capacity)).cast("long")})
