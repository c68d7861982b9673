"""Plain answers for small inputs."""

import hashlib
import re
from collections import defaultdict

import numpy as np

from coverdp.llm import textkit

WORD = re.compile(r"[^\x20\x09-\x0D]+")
FOLD = str.maketrans({chr(i): chr(i + 32) for i in range(65, 91)})


def shingle_sets(rows, k):
    out = {}
    for i, text in rows:
        w = WORD.findall((text or "").translate(FOLD))
        out[i] = {tuple(w[j : j + k]) for j in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())
    return out


def linked(sets):
    """The least id reachable over pairs at 0.8."""
    ids, up = sorted(sets), {i: i for i in sets}

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    inverted = defaultdict(list)
    for i in ids:
        for g in sets[i]:
            inverted[g].append(i)
    for i in ids:
        counts = defaultdict(int)
        for g in sets[i]:
            for j in inverted[g]:
                if j > i:
                    counts[j] += 1
        for j, n in counts.items():
            if 100 * n >= 80 * (len(sets[i]) + len(sets[j]) - n):
                a, b = top(i), top(j)
                up[max(a, b)] = min(a, b)
    return {i: top(i) for i in ids}


def repeats(rows, length=50):
    """doc_id -> (bytes, removed, spans, SHA-256 of the rest)."""
    least, out = {}, {}
    raw = {i: (t or "").encode() for i, t in rows}
    for i, b in raw.items():
        for p in range(len(b) - length + 1):
            w = b[p : p + length]
            least[w] = min(i, least.get(w, i))
    for i, b in raw.items():
        gone = bytearray(len(b))
        for p in range(len(b) - length + 1):
            if least[b[p : p + length]] < i:
                gone[p : p + length] = b"\1" * length
        spans = len(re.findall(rb"\x01+", bytes(gone)))
        out[i] = len(b), sum(gone), spans, hashlib.sha256(bytes(x for x, g in zip(b, gone, strict=True) if not g)).hexdigest()
    return out


def base_statistics(text):
    text = text or ""
    w = WORD.findall(text)
    windows = defaultdict(list)
    for i in range(len(w) - 2):
        windows[tuple(w[i : i + 3])].append(i)
    covered = {i + j for places in windows.values() if len(places) > 1 for i in places for j in range(3)}
    lines = [x for x in text.split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(covered)


def paragraphs(text, least=20, passage=32, reach=16):
    """(first word, kind, first byte, end, words) of a text's lines and passages."""
    raw = (text or "").encode()
    found = [(m.start(), m.end()) for m in re.finditer(rb"[^\x20\x09-\x0D]+", raw)]
    low = [raw[a:z].lower() for a, z in found]
    at = 0
    for line in raw.split(b"\n"):
        own = [i for i, (a, _) in enumerate(found) if at <= a < at + len(line)]
        if len(own) >= least:
            yield own[0], 0, at, min(at + len(line) + 1, len(raw)), b" ".join(low[own[0] : own[-1] + 1]).decode()
        at += len(line) + 1
    h = [textkit.span_hashes(np.frombuffer(w, np.uint8), np.array([0]), np.array([len(w)]))[0] for w in low]
    with np.errstate(over="ignore"):
        pair = [int(textkit.mix(np.array([a * textkit.STEP + b]))[0] >> np.uint64(1)) for a, b in zip(h, h[1:])]
    for i, x in enumerate(pair):
        if i + passage <= len(low) and all(x < y for y in pair[max(0, i - reach) : i]) and all(x <= y for y in pair[i + 1 : i + reach + 1]):
            yield i, 1, found[i][0], found[i + passage - 1][1], b" ".join(low[i : i + passage]).decode()
