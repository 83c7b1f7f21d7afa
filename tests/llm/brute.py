"""Plain-Python versions of the corpus operators, for small fixtures."""

import hashlib
import re
import zlib

WORD = re.compile(rb"[^\x20\x09-\x0D]+")


def word_windows(docs, n=20):
    seen, out = set(), {}
    for doc, text in sorted(docs):
        w = WORD.findall((text or "").encode())
        drop = [False] * len(w)
        for s in range(len(w) - n + 1):
            key = tuple(w[s : s + n])
            if key in seen:
                drop[s : s + n] = [True] * n
            seen.add(key)
        kept = [x for x, d in zip(w, drop, strict=True) if not d]
        out[doc] = (len(w), sum(drop), hashlib.sha256(b" ".join(kept)).hexdigest())
    return out


def byte_windows(docs, n=400):
    count = {}
    raw = [(d, (t or "").encode()) for d, t in docs]
    for _, t in raw:
        for s in range(len(t) - n + 1):
            count[t[s : s + n]] = count.get(t[s : s + n], 0) + 1
    out = []
    for d, t in raw:
        drop = bytearray(len(t))
        for s in range(len(t) - n + 1):
            if count[t[s : s + n]] > 1:
                drop[s : s + n] = b"\x01" * n
        spans = len(re.findall(b"\x01+", bytes(drop)))
        kept = bytes(c for c, x in zip(t, drop, strict=True) if not x)
        out.append((d, len(t), sum(drop), spans, hashlib.sha256(kept).hexdigest()))
    return out


def crc(doc):
    return zlib.crc32(str(doc).encode())
