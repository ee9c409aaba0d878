"""Document statistics for quality models: counts over whole texts, a block of documents at a time."""

from __future__ import annotations

import numpy as np

from cityweave.llm.kernel import Words, exact_names, mix, window_hash

SYMBOLS = np.zeros(256, bool)
SYMBOLS[list(b"#*$%&|<>")] = True
CONTINUED = np.zeros(256, bool)
CONTINUED[0x80:0xC0] = True
_DIGIT, _UPPER, _BANG, _PIPE = (np.zeros(256, bool) for _ in range(4))
_DIGIT[48:58] = True
_UPPER[65:91] = True
_BANG[ord("!")] = True
_PIPE[ord("|")] = True

#: Words of a window whose return marks repetition.
WINDOW = 5

BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
FEATURES = ("log_words", "word_length", "symbol_share", "dup_line_share", "repeat_share", "distinct_share", "upper_share", "bang_share", "pipe_share", "digit_share", "line_words")

# The more of these, the lower the quality may be scored, never the higher.
DECREASING = ("symbol_share", "dup_line_share", "repeat_share", "bang_share", "pipe_share")


def _per_doc(flags: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    seen = np.concatenate(([0], np.cumsum(flags)))
    return seen[offsets[1:]] - seen[offsets[:-1]]


def _runs(doc: np.ndarray, name: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """An order that brings equal (doc, name) together, earlier ones first, and whether each repeats the one before."""
    key = doc * (int(name.max(initial=0)) + 1) + name
    order = np.argsort(key, kind="stable")
    again = np.zeros(len(order), bool)
    again[1:] = key[order][1:] == key[order][:-1]
    return order, again


def _window_runs(doc: np.ndarray, at: np.ndarray, names: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The same for windows of names that begin at `at`: brought together by a hash, and told apart by the names themselves."""
    value = window_hash(mix(names.astype(np.uint64) + np.uint64(1)), tuple(range(WINDOW)), WINDOW)[at] if len(at) else np.zeros(0, np.uint64)
    key = mix(value + mix(doc[at].astype(np.uint64) + np.uint64(1)))
    order = np.argsort(key, kind="stable")

    def same(order: np.ndarray) -> np.ndarray:
        a, b = at[order][1:], at[order][:-1]
        out = doc[a] == doc[b]
        for k in range(WINDOW):
            out &= names[a + k] == names[b + k]
        return out

    equal = same(order)
    if (equal != (key[order][1:] == key[order][:-1])).any():
        # one hash for different windows: sorted by the names
        order = np.lexsort((at, *(names[at + k] for k in range(WINDOW)), doc[at]))
        equal = same(order)
    again = np.zeros(len(order), bool)
    again[1:] = equal
    return order, again


def statistics(data: np.ndarray, offsets: np.ndarray) -> dict[str, np.ndarray]:
    """Counts for each document of a block; see BASE and FEATURES."""
    n_docs = len(offsets) - 1
    words = Words(data, offsets)
    inside = np.zeros(len(data) + 1, np.int64)
    np.add.at(inside, words.start, 1)
    np.add.at(inside, words.end, -1)
    in_word = np.cumsum(inside[:-1]) > 0
    names = exact_names(data[in_word], words.end - words.start)
    points = ~CONTINUED[data]
    out = {
        "n_words": words.count.astype(np.int64),
        "word_chars": _per_doc(in_word & points, offsets),
        "n_symbols": _per_doc(SYMBOLS[data], offsets),
    }

    # lines: cut at line feeds and at document ends
    cuts = np.flatnonzero(data == 10)
    n_lines = np.diff(np.searchsorted(cuts, offsets)) + 1
    starts = np.sort(np.concatenate((offsets[:-1], cuts + 1)))
    ends = np.sort(np.concatenate((offsets[1:], cuts)))
    line_doc = np.repeat(np.arange(n_docs), n_lines)
    lines = exact_names(data[data != 10], ends - starts)
    worded = np.searchsorted(words.start, ends) > np.searchsorted(words.start, starts)
    order, again = _runs(line_doc[worded], lines[worded])
    out["n_dup_lines"] = np.bincount(line_doc[worded][order][again], minlength=n_docs)

    # windows of words that come twice or more
    at = words.windows(WINDOW)
    order, again = _window_runs(words.doc, at, names)
    twice = again.copy()
    twice[:-1] |= again[1:]
    mark = np.zeros(len(names) + 1, np.int64)
    np.add.at(mark, at[order][twice], 1)
    np.add.at(mark, at[order][twice] + WINDOW, -1)
    out["n_repeat_words"] = np.bincount(words.doc[np.cumsum(mark[:-1]) > 0], minlength=n_docs)

    order, again = _runs(words.doc, names)
    n, size = np.maximum(out["n_words"], 1), np.maximum(np.diff(offsets), 1)
    out |= {
        "log_words": np.log1p(out["n_words"]),
        "word_length": out["word_chars"] / n,
        "symbol_share": out["n_symbols"] / n,
        "dup_line_share": out["n_dup_lines"] / np.maximum(n_lines, 1),
        "repeat_share": out["n_repeat_words"] / n,
        "distinct_share": np.bincount(words.doc[order][~again], minlength=n_docs) / n,
        "upper_share": _per_doc(_UPPER[data], offsets) / size,
        "bang_share": _per_doc(_BANG[data], offsets) / n,
        "pipe_share": _per_doc(_PIPE[data], offsets) / n,
        "digit_share": _per_doc(_DIGIT[data], offsets) / size,
        "line_words": np.minimum(out["n_words"] / np.maximum(n_lines, 1), 1000.0),
    }
    return out


def features(stats: dict[str, np.ndarray]) -> np.ndarray:
    return np.stack([stats[f] for f in FEATURES], axis=1).astype(np.float64)
