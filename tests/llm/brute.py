"""Plain versions of the operators' results, one document or pair at a time."""

import hashlib
import re
import zlib

import xxhash

EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def luhn(digits):
    total = 0
    for k, d in enumerate(reversed(digits)):
        d = int(d)
        if k % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def digits(x):
    return re.sub("[^0-9]", "", x)


def base_spans(text):
    text = text or ""
    out = [(m.start(), 0, m.end()) for m in EMAIL.finditer(text)]
    out += [(m.start(), 1, m.end()) for m in IP.finditer(text) if all(int(p) <= 255 for p in m.group().split("."))]
    out += [(m.start(), 2, m.end()) for m in CARD.finditer(text) if 12 <= len(digits(m.group())) <= 19 and luhn(digits(m.group()))]
    out += [(m.start(), 3, m.end()) for m in PHONE.finditer(text) if 9 <= len(digits(m.group())) <= 15]
    return sorted(out)


def pii_row(text):
    spans = base_spans(text)
    joined = ",".join(f"{('email', 'ip', 'card', 'phone')[k]}:{a}:{b}" for a, k, b in spans)
    return tuple(sum(k == n for _, k, _ in spans) for n in range(4)) + (hashlib.sha256(joined.encode()).hexdigest(),)


def lower(text):
    return re.sub("[A-Z]", lambda m: m.group().lower(), text or "")


def fingerprint(text):
    words = WORD.findall(lower(text))
    if not words:
        return 0
    shingles = [" ".join(words[k : k + 3]) for k in range(max(1, len(words) - 2))]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def components(nodes, linked):
    root = {n: n for n in nodes}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in linked:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {n: find(n) for n in nodes}


def simhash_rows(docs, budget=2):
    fps = {d: fingerprint(t) for d, t in docs}
    ids = sorted(fps)
    near = [(a, b) for i, a in enumerate(ids) for b in ids[i + 1 :] if bin(fps[a] ^ fps[b]).count("1") <= budget]
    comp = components(ids, near)
    return {d: (f"{fps[d]:016x}", comp[d]) for d in ids}


def piece_rows(docs, tokenizer, capacity=4096):
    import numpy as np

    out = {}
    for d, t in docs:
        ids = tokenizer.encode(t or "", add_special_tokens=False).ids + [1]
        for k, at in enumerate(range(0, len(ids), capacity)):
            part = np.array(ids[at : at + capacity], "<u4")
            out[d, k] = (at, len(part), zlib.crc32(part.tobytes()))
    return out


def repeats_row(docs, size=100):
    """doc_id -> (n_bytes, n_removed, n_spans, sha256 of what is left)."""
    seen, covered, texts = set(), {}, {}
    for d, t in sorted(docs, key=lambda x: x[0]):
        b = (t or "").encode()
        mark = bytearray(len(b))
        for k in range(len(b) - size + 1):
            s = b[k : k + size]
            if s in seen:
                mark[k : k + size] = b"\1" * size
            else:
                seen.add(s)
        covered[d], texts[d] = mark, b
    out = {}
    for d, mark in covered.items():
        runs = len(re.findall(b"\1+", bytes(mark)))
        left = bytes(x for x, m in zip(texts[d], mark) if not m)
        out[d] = (len(mark), sum(mark), runs, hashlib.sha256(left).hexdigest())
    return out


def base_statistics(text):
    words = WORD.findall(text or "")
    lines, seen, dup = (text or "").split("\n"), set(), 0
    for line in lines:
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    windows = {}
    for k in range(len(words) - 4):
        windows.setdefault(tuple(words[k : k + 5]), []).append(k)
    repeated = {k + j for at in windows.values() if len(at) > 1 for k in at for j in range(5)}
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text or "")), dup, len(repeated)
