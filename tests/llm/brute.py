"""Plain Python versions of the operators, for small tables."""

import hashlib
from collections import Counter

import xxhash


def repeats(docs, depth=400):
    texts = [(t or "").encode() for _, t in docs]
    seen = Counter(t[i : i + depth] for t in texts for i in range(len(t) - depth + 1))
    out = []
    for (doc_id, _), t in zip(docs, texts):
        gone = bytearray(len(t))
        for i in range(len(t) - depth + 1):
            if seen[t[i : i + depth]] > 1:
                gone[i : i + depth] = b"\1" * depth
        spans = sum(1 for i in range(len(t)) if gone[i] and (i == 0 or not gone[i - 1]))
        out.append((doc_id, len(t), sum(gone), spans, hashlib.sha256(bytes(c for c, g in zip(t, gone) if not g)).hexdigest()))
    return out


def passages(docs, words=51):
    """Words of each text under a run of that many words that a row with another key (doc_id, text) has too."""
    texts = [(t or "").encode().split() for _, t in docs]
    where = {}
    for key, t in zip(docs, texts):
        for i in range(len(t) - words + 1):
            where.setdefault(tuple(t[i : i + words]), set()).add(key)
    out = []
    for t in texts:
        hit = {k for i in range(len(t) - words + 1) if len(where[tuple(t[i : i + words])]) > 1 for k in range(i, i + words)}
        out.append(len(hit))
    return out


def simhash(docs):
    def fp(text):
        words = (text or "").encode().lower().split()
        if not words:
            return 0
        shingles = [b" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
        votes = [0] * 64
        for s in shingles:
            h = xxhash.xxh64_intdigest(s, 42)
            for i in range(64):
                votes[i] += h >> i & 1
        return sum(1 << i for i in range(64) if 2 * votes[i] > len(shingles))

    fps = [fp(t) for _, t in docs]
    root = list(range(len(docs)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(docs)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 2:
                root[find(i)] = find(j)
    lead = {}
    for i, (doc_id, _) in enumerate(docs):
        lead[find(i)] = min(lead.get(find(i), doc_id), doc_id)
    return [(doc_id, f"{fps[i]:016x}", lead[find(i)]) for i, (doc_id, _) in enumerate(docs)]
