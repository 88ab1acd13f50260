"""Plain versions of the operators, over lists in memory."""

from __future__ import annotations

import hashlib
import zlib
from collections import Counter, defaultdict

import numpy as np
import xxhash


def repeats(rows: list[tuple[int, str]], length: int = 400) -> list[tuple]:
    seen: Counter = Counter()
    bodies = [(i, (t or "").encode()) for i, t in rows]
    for _, b in bodies:
        for p in range(len(b) - length + 1):
            seen[xxhash.xxh3_128_digest(b[p : p + length])] += 1
    out = []
    for i, b in bodies:
        gone = np.zeros(len(b) + 1, int)
        for p in range(len(b) - length + 1):
            if seen[xxhash.xxh3_128_digest(b[p : p + length])] > 1:
                gone[p] += 1
                gone[p + length] -= 1
        mask = np.cumsum(gone)[:-1] > 0
        left = bytes(np.frombuffer(b, np.uint8)[~mask])
        runs = int((np.diff(np.r_[0, mask.astype(int)]) == 1).sum())
        out.append((i, len(b), int(mask.sum()), runs, hashlib.sha256(left).hexdigest()))
    return out


def fingerprint(text: str | None, n: int = 3) -> int:
    lowered = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words, word = [], ""
    for c in lowered:
        if c == " " or "\t" <= c <= "\r":
            words += [word] * bool(word)
            word = ""
        else:
            word += c
    words += [word] * bool(word)
    if not words:
        return 0
    parts = [" ".join(words[i : i + n]) for i in range(len(words) - n + 1)] or [" ".join(words)]
    hashes = [xxhash.xxh64_intdigest(p.encode(), seed=42) for p in parts]
    return sum(1 << k for k in range(64) if 2 * sum(h >> k & 1 for h in hashes) > len(hashes))


def groups(prints: list[tuple[int, int]], radius: int = 2) -> dict[int, int]:
    """Smallest id reachable, by comparing all pairs of fingerprints."""
    root = list(range(len(prints)))

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    bits = np.array([p for _, p in prints], np.uint64)
    for i in range(len(prints)):
        for j in (np.flatnonzero(np.bitwise_count(bits[i + 1 :] ^ bits[i]) <= radius) + i + 1).tolist():
            root[find(i)] = find(j)
    least: dict[int, int] = {}
    for i, (d, _) in enumerate(prints):
        least[find(i)] = min(least.get(find(i), d), d)
    return {d: least[find(i)] for i, (d, _) in enumerate(prints)}


def token_bytes(text: str | None, tokenizer) -> bytes:
    return np.array(tokenizer.encode(text or "", add_special_tokens=False).ids, "<u4").tobytes()


def piece_rows(doc_id, text, tokenizer, capacity: int = 2048) -> list[tuple]:
    body = token_bytes(text, tokenizer) + bytes(4)
    return [(doc_id, j, a // 4, len(body[a : a + 4 * capacity]) // 4, zlib.crc32(body[a : a + 4 * capacity])) for j, a in enumerate(range(0, len(body), 4 * capacity))]


def check_packing(rows: list, capacity: int = 2048) -> int:
    """Tests that sequences hold their pieces gaplessly; returns how many there are."""
    by = defaultdict(list)
    for r in rows:
        by[r["sequence_id"]].append((r["offset"], r["length"]))
    for held in by.values():
        at = 0
        for offset, length in sorted(held):
            assert offset == at
            at += length
        assert at <= capacity
    return len(by)


def urls(rows: list[tuple[int, str | None]], rules: list[tuple[str, str, str]]) -> list[tuple]:
    out = []
    for i, url in rows:
        host = path = ""
        if url is not None and "://" in url:
            rest = url.split("://", 1)[1]
            cut = min([rest.find(c) for c in "/?#" if c in rest] or [len(rest)])
            host, rest = rest[:cut], rest[cut:]
            host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host)
            path = rest[: min([rest.find(c) for c in "?#" if c in rest] or [len(rest)])]
        fits = [(len(h + p), h + p, v) for h, p, v in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
        best = max(fits, default=(0, None, "allow"))
        out.append((i, host, path, best[1], best[2]))
    return out


def shingles(text: str | None, n: int = 5) -> frozenset:
    words = (text or "").encode().lower().split()
    return frozenset(b" ".join(words[i : i + n]) for i in range(max(len(words) - n + 1, min(len(words), 1))))


def similar_groups(rows: list[tuple[int | None, str | None]], least: float = 0.8) -> list[tuple[int | None, int | None]]:
    """Each row's id and the smallest id reachable, by comparing the shingle sets of all pairs."""
    sets = [shingles(t) for _, t in rows]
    name = list(range(len(rows)))
    for i in range(len(rows)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if name[i] != name[j] and both >= least * (len(sets[i]) + len(sets[j]) - both) - 1e-9:
                old, new = name[i], name[j]
                name = [new if x == old else x for x in name]
    ids = defaultdict(list)
    for (i, _), c in zip(rows, name, strict=True):
        if i is not None:
            ids[c].append(i)
    return [(i, min(ids[c], default=None)) for (i, _), c in zip(rows, name, strict=True)]
