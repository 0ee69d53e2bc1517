"""Plain versions of the operators that SQL cannot express."""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter, defaultdict

WORD = re.compile("[^\x20\x09-\x0d]+")


def lower(text):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")


def good_turing(n, cut=5):
    d = {}
    common = (cut + 1) * n[cut + 1] / n[1] if n[1] else 0.0
    for r in range(1, cut + 1):
        v = ((r + 1) * n[r + 1] / (r * n[r]) - common) / (1 - common) if n[r] and n[r + 1] and common < 1 else 0.0
        d[r] = v if 0 < v < 1 else 1 - 0.5 / r
    return d


class Katz:
    """Backoff model from dictionaries, one conditional probability at a time; contexts are tuples, oldest word first."""

    def __init__(self, rows, order=2):
        self.order, self.uni, self.grams = order, Counter(), defaultdict(Counter)
        for doc_id, text in rows:
            if doc_id is None or zlib.crc32(str(doc_id).encode()) % 7 != 2:
                words = WORD.findall(lower(text)) + [None]
                self.uni.update(words)
                for k, w in enumerate(words):
                    history = self.history(words, k)
                    for n in range(1, len(history) + 1):
                        self.grams[history[-n:]][w] += 1
        self.n, self.v = sum(self.uni.values()), len(self.uni)
        self.d = {0: good_turing(Counter(self.uni.values()))}
        for n in range(1, order):
            self.d[n] = good_turing(Counter(r for h, own in self.grams.items() if len(h) == n for r in own.values()))
        freed = sum((1 - self.d[0].get(c, 1)) * c for c in self.uni.values()) / self.n if self.n else 1.0
        self.scale = 1.0 if freed > 0 else self.n / (self.n + 1)
        self.unk = freed if freed > 0 else 1 / (self.n + 1)

    def history(self, words, k):
        return tuple([("<start>",), *[("w", x) for x in words[:k]]][-(self.order - 1) :])

    def p(self, w, h=()):
        if not h:
            c = self.uni.get(w, 0)
            return self.scale * self.d[0].get(c, 1) * c / self.n if c else self.unk
        own = self.grams.get(h)
        if not own:
            return self.p(w, h[1:])
        d, count = self.d[len(h)], sum(own.values())
        freed = sum((1 - d.get(r, 1)) * r for r in own.values()) / count
        keep = 1.0 if freed > 0 else count / (count + 1)
        freed = freed if freed > 0 else 1 / (count + 1)
        if w in own:
            return keep * d.get(own[w], 1) * own[w] / count
        return freed / (1 - sum(self.p(x, h[1:]) for x in own)) * self.p(w, h[1:])

    def score(self, text):
        words = WORD.findall(lower(text)) + [None]
        base = sum(math.log10((self.uni.get(w, 0) + 1) / (self.n + self.v + 1)) for w in words)
        return len(words), sum(w in self.uni for w in words), base, sum(math.log10(self.p(w, self.history(words, k))) for k, w in enumerate(words))
