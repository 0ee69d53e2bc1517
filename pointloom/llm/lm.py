"""LM scoring by a Katz backoff model of any order with Good-Turing discounts and exactly normalised backoff weights.

``P(w)``: discounted counts over all training tokens; the mass that discounting frees is the probability of the one
unknown word, so the known words and it sum to 1. ``P(w | h)`` for a context ``h`` of one or more words: the discounted count of
(h, w) over the count of h where that was seen, else ``alpha(h) P(w | h without its oldest word)``, with ``alpha(h)`` = what
discounting freed in h over the shorter context's mass of all words not seen after h. A context that was never seen leaves
everything to the shorter one. A text starts in a context of its own (its first words have that many words less) and ends with
one end token.

Tables are partitioned by the last word of the context and hold arrays, never one row a token. Every shorter context ends in
the same word, so the whole recursion is evaluated inside a partition, and the counts of the lower orders are sums there:

1. Distinct words meet by a shuffle (:mod:`pointloom.llm.wordshuffle`): training counts are summed, words numbered, and both
   go back to the texts' chunks.
2. By chunk, the distinct n-grams with their training counts and the documents that hold them are dealt to the partition
   of their context's last word, one block a chunk and partition.
3. A partition merges its blocks into the tables of all orders. One job sums the counts of counts, from which the discounts
   follow; a second job, over the same shuffled blocks, forms the backoff weights order by order, evaluates every n-gram and adds
   up each document's part.
4. The parts of a document meet by chunk.

Frequent words are spread: a context that ends in one of them goes to a partition by its second last word (or, where it has
none, by the next word). Longer contexts are then still whole; only the table of pairs after such a word is cut up. Its
counts are taken in step 1, where a word's partition also counts what frequent words stand before it, and its sums (at most
``MOST_HOT`` rows) are sent to all. Which words count as frequent is read off a sample; it changes places, never results.

Good-Turing: counts up to ``CUT`` are discounted as usual, for each order by itself; where a count of counts is zero or a discount
leaves (0, 1], the discount is 1 - 0.5 / r. A context without any discounted count keeps 1 / (count + 1) for unseen words.

Defined cases: null and empty texts are one end token; a null doc_id is a training row; repeated rows count as often as
they occur; without training rows every word is unknown with probability 1 (scores 0); an empty table gives an empty
result; extra columns are ignored.
"""

from __future__ import annotations

import pickle
import zlib
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F

from pointloom.llm.common import lean, materialize
from pointloom.llm.wordshuffle import BLOCK, Codes, assembled, by_bucket, by_chunk, chunks, n_buckets, pack, position_rows, row_of, source, unpack

ORDER = 3
CUT = 5
#: A word of more than this share of the sample's tokens is spread over ``SPREAD`` partitions; the sample's documents, and
#: the most words that are spread.
HOT, SPREAD, SAMPLE, MOST_HOT = 0.001, 64, 5_000, 1_000
#: Buckets of contexts in a partition, merged one after the other, and the document sums that a task holds.
BUCKETS, HELD_DOCS = 4, 2_000_000
#: Keys are numbers below this.
WIDE = 2**62
#: The end token; no word is empty.
END = b""
#: The number of the starting context; words are numbered from 1. No word further back: NO_WORD.
START, NO_WORD = 0, -1


# the model -----------------------------------------------------------------------------------------------------


def discounts(n: np.ndarray) -> np.ndarray:
    """Good-Turing factors of counts 0..CUT (1 above); n[r] is how many events were seen r times, r <= CUT + 1."""
    n = np.asarray(n, np.float64)
    d = np.ones(CUT + 2)
    common = (CUT + 1) * n[CUT + 1] / n[1] if n[1] else 0.0
    for r in range(1, CUT + 1):
        ratio = ((r + 1) * n[r + 1] / (r * n[r]) - common) / (1 - common) if n[r] and n[r + 1] and common < 1 else 0.0
        d[r] = ratio if 0 < ratio < 1 else 1 - 0.5 / r
    return d


class Unigrams:
    """P(w) as a function of the training count; count 0 is the one unknown word."""

    def __init__(self, n: np.ndarray, tokens: int, distinct: int):
        self.tokens, self.distinct, self.d = tokens, distinct, discounts(n)
        r = np.arange(CUT + 1)
        freed = float((n[: CUT + 1] * r * (1 - self.d[: CUT + 1])).sum()) / tokens if tokens else 1.0
        self.scale = 1.0 if freed > 0 else tokens / (tokens + 1)
        self.unknown = freed if freed > 0 else 1 / (tokens + 1)

    def p(self, c: np.ndarray) -> np.ndarray:
        seen = self.scale * self.d[np.minimum(c, CUT + 1)] * c / max(1, self.tokens)
        return np.where(c > 0, seen, self.unknown)

    def base(self, c: np.ndarray) -> np.ndarray:
        return np.log10((c + 1) / (self.tokens + self.distinct + 1))


def context_sums(h: np.ndarray, r: np.ndarray, p: np.ndarray):
    """Of contexts (numbered from 0), a row each: [count, m_1..m_CUT, the shorter context's mass] of what was seen after it."""
    n, cols = int(h.max(initial=-1)) + 1, [r, *((r == k) for k in range(1, CUT + 1)), np.where(r > 0, p, 0)]
    return np.stack([np.bincount(h, x, n) for x in cols], axis=1)


def backoff(sums: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(alpha, factor on the seen pairs) of contexts by their sums; contexts never seen have alpha 1."""
    count, m, mass = sums[:, 0], sums[:, 1 : CUT + 1], sums[:, CUT + 1]
    freed = (m * np.arange(1, CUT + 1) * (1 - d[1 : CUT + 1])).sum(axis=1) / np.maximum(count, 1)
    keep = np.where(freed > 0, 1.0, count / (count + 1))
    freed = np.where(freed > 0, freed, 1 / (count + 1))
    return np.where(count > 0, freed / np.maximum(1 - mass, 1e-300), 1.0), keep


def level_p(h, r, sums, lower, d) -> np.ndarray:
    """P(w | h) of one order: the own count first, else one step back to ``lower``; ``h`` numbers the rows of ``sums``."""
    alpha, keep = backoff(sums, d)
    seen = keep[h] * d[np.minimum(r, CUT + 1)] * r / np.maximum(sums[h, 0], 1)
    return np.where(r > 0, seen, alpha[h] * lower)


# chunks --------------------------------------------------------------------------------------------------------


def trains(doc_id: int | None) -> bool:
    return doc_id is None or zlib.crc32(str(doc_id).encode()) % 7 != 2


def keys(text: str) -> list[bytes]:
    """ASCII-lower-cased words and the end token; bytes.lower and bytes.split know ASCII only."""
    return [*text.encode().lower().split(), END]


def word_of(key: bytes) -> bytes:
    return key


def frequent_words(docs: DataFrame) -> list[bytes]:
    """Words of a sample of the documents that are frequent there."""
    some = min(1.0, SAMPLE / max(1, docs.count()))
    share = F.pmod(F.xxhash64(F.lit(3), "doc_id", "text"), F.lit(1_000_003)) < int(1_000_003 * some)

    def run(batches):
        for b in batches:
            for text in b.column(0):
                words, n = np.unique(np.array(keys(text.as_py() or ""), object), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(words.tolist(), pa.binary()), pa.array(n.astype(np.int64))], ["word", "n"])

    counts = materialize(docs.where(share).select(F.col("text").cast("string")).mapInArrow(lean(run), "word binary, n long").groupBy("word").agg(F.sum("n").alias("n")))
    total = counts.agg(F.sum("n")).first()[0] or 0
    rows = counts.where((F.col("n") > HOT * total) & (F.length("word") > 0)).orderBy(F.col("n").desc(), "word").limit(MOST_HOT - 1).collect()
    return [bytes(r["word"]) for r in rows]


def _after_hot(ends: np.ndarray, codes: np.ndarray, hot_of: np.ndarray, n_hot: int, train: np.ndarray):
    """Of a chunk's tokens: sorted distinct (word, frequent word before it) as word * n_hot + number, and their training counts.
    Number 0 is the start of a text."""
    starts = ends - np.diff(ends, prepend=0)
    before = np.concatenate(([0], hot_of[codes[:-1]]))
    before[starts] = 0
    at = np.flatnonzero(before >= 0)
    pairs, of = np.unique(codes[at].astype(np.int64) * n_hot + before[at], return_inverse=True)
    return pairs, np.bincount(of, train[at], len(pairs)).astype(np.int64)


def _hot_numbers(words: list[bytes], hot: dict[bytes, int]) -> np.ndarray:
    return np.fromiter((hot.get(w, -1) for w in words), np.int64, len(words))


def _word_blocks(hot: dict[bytes, int], buckets: int):
    """A block a chunk and bucket: the words, their training counts, and pairs with frequent words before them."""
    n_hot = len(hot) + 1

    def run(batches):
        for chunk, words, bounds, ids, ends, codes in chunks(batches, keys, word_of, buckets):
            train = np.repeat(np.array([trains(i) for i in ids]), np.diff(ends, prepend=0))
            n = np.bincount(codes[train], minlength=len(words))
            pairs, r = _after_hot(ends, codes, _hot_numbers(words, hot), n_hot, train)
            cuts = np.searchsorted(pairs, bounds * n_hot)
            for k in range(buckets):
                part = words[bounds[k] : bounds[k + 1]]
                if part:
                    sizes, mine = np.fromiter(map(len, part), np.int64, len(part)), slice(cuts[k], cuts[k + 1])
                    own = pairs[mine] - bounds[k] * n_hot
                    yield row_of(k, chunk, pack(sizes, np.frombuffer(b"".join(part), np.uint8), n[bounds[k] : bounds[k + 1]], (own // n_hot).astype(np.uint32), (own % n_hot).astype(np.uint16), r[mine].astype(np.uint32)))

    return run


def _numbered(buckets: int, n_hot: int):
    """Every block gets its words' training counts and numbers and its pairs' counts. A row of bucket -2 a task has the sums: distinct
    words, tokens, how many words were seen 1..CUT + 1 times; one of bucket -3 has, by frequent word, the sums over what stands
    after it: counts, m_1..m_CUT + 1, words seen 1..CUT times, and the tokens of all others."""

    def run(batches):
        distinct = tokens = 0
        n, after = np.zeros(CUT + 2, np.int64), np.zeros((n_hot, 2 * CUT + 3), np.int64)
        for bucket, rows in groupby((r for b in batches for r in b.to_pylist()), key=lambda r: r["bucket"]):
            table, names, own, counts, pairs, seen = Codes(), [], [], [], [], []
            for r in rows:
                sizes, text, count, word, before, times = unpack(r["data"])
                text, ends = text.tobytes(), np.cumsum(sizes).tolist()
                codes = np.array([table[text[a:b]] for a, b in zip([0, *ends], ends)], np.int64)
                names.append(r["chunk"])
                own.append(codes)
                counts.append(count)
                pairs.append(codes[word] * n_hot + before)
                seen.append(times)
            totals = np.bincount(np.concatenate(own), np.concatenate(counts), len(table)).astype(np.int64)
            keys_, of = np.unique(np.concatenate(pairs), return_inverse=True)
            c2 = np.bincount(of, np.concatenate(seen), len(keys_)).astype(np.int64)
            distinct, tokens = distinct + int((totals > 0).sum()), tokens + int(totals.sum())
            n += np.bincount(totals[(totals > 0) & (totals <= CUT + 1)], minlength=CUT + 2)
            known = c2 > 0
            h, r, c = (keys_ % n_hot)[known], c2[known], totals[keys_ // n_hot][known]
            columns = [r, *(r == k for k in range(1, CUT + 2)), *(c == k for k in range(1, CUT + 1)), np.where(c > CUT, c, 0)]
            after += np.stack([np.bincount(h, x, n_hot).astype(np.int64) for x in columns], axis=1)
            lo = 0
            for chunk, codes, p in zip(names, own, pairs, strict=True):
                gid = codes * buckets + bucket + 1
                yield row_of(bucket, chunk, pack(totals[codes], gid, c2[of[lo : lo + len(p)]].astype(np.uint32)))
                lo += len(p)
        yield row_of(-2, -1, pack(np.array([distinct, *n[1:].tolist(), tokens])))
        at = np.flatnonzero(after.any(axis=1))
        yield row_of(-3, -1, pack(at, after[at].ravel()))

    return run


def _hot_sums(counted: DataFrame, n_hot: int, uni: Unigrams) -> tuple[np.ndarray, np.ndarray]:
    """Rows of :func:`context_sums` of the frequent words, and how many pairs after them were seen 0..CUT + 1 times."""

    def run(batches):
        for b in batches:
            for data in b.column(0):
                at, values = unpack(data.as_py())
                values = values.reshape(len(at), 2 * CUT + 3)
                yield pa.RecordBatch.from_arrays([pa.array(at), *map(pa.array, np.ascontiguousarray(values.T))], ["h", *(f"x{k}" for k in range(2 * CUT + 3))])

    names = [f"x{k}" for k in range(2 * CUT + 3)]
    rows = counted.where("bucket = -3").select("data").mapInArrow(lean(run), "h long, " + ", ".join(f"{x} long" for x in names))
    total = np.zeros((n_hot, 2 * CUT + 3), np.int64)
    # at most MOST_HOT rows
    for r in rows.groupBy("h").agg(*[F.sum(x).alias(x) for x in names]).collect():
        total[r["h"]] = [r[x] for x in names]
    few = uni.p(np.arange(1, CUT + 1))
    mass = total[:, CUT + 2 : 2 * CUT + 2] @ few + uni.scale * total[:, -1] / max(1, uni.tokens)
    return np.hstack([total[:, : CUT + 1].astype(np.float64), mass[:, None]]), np.concatenate(([0], total[:, 1 : CUT + 2].sum(axis=0)))


# n-grams -------------------------------------------------------------------------------------------------------


def _spread(x: np.ndarray) -> np.ndarray:
    x = x.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9) >> np.uint64(32)


def _dense(key: np.ndarray) -> tuple[np.ndarray, int]:
    """Numbers 0, 1, ... in the order of the keys, and how many there are."""
    order = np.argsort(key)
    at = key[order]
    rank = np.cumsum(np.concatenate(([False], at[1:] != at[:-1]))[: len(at)])
    out = np.empty(len(key), np.int64)
    out[order] = rank
    return out, int(rank[-1]) + 1 if len(rank) else 1


def _distinct(columns: list[np.ndarray], widths: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Order of the rows by their columns, and where in it new rows start. Columns are folded into one number; where that would grow
    too large, what there is so far is numbered anew."""
    key, total = columns[0].astype(np.int64), widths[0]
    for c, w in zip(columns[1:], widths[1:], strict=True):
        if total * w >= WIDE:
            key, total = _dense(key)
            if total * w >= 2**63:
                c, w = _dense(c)
        key, total = key * w + c, total * w
    order = np.argsort(key)
    key = key[order]
    return order, np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1]))[: len(key)])


def _narrow(x: np.ndarray) -> np.ndarray:
    """Numbers that are not negative in the smallest type that holds them."""
    most = x.max(initial=0)
    return x.astype(np.uint8 if most < 1 << 8 else np.uint16 if most < 1 << 16 else np.uint32 if most < 1 << 32 else np.int64)


def _deal(uni: Unigrams, parts: int, order: int, n_hot: int):
    """A chunk's positions and its words' counts and numbers -> blocks of n-grams, and one row of document sums."""

    def done(chunk, ids, ends, codes, n_words, hot_of, answers):
        c, gid, c2 = (np.concatenate(x) for x in zip(*map(unpack, answers), strict=True))
        if len(c) != n_words:
            raise RuntimeError("two reads of the documents differ; write them to a table first")
        size = np.diff(ends, prepend=0)
        starts, doc = ends - size, np.repeat(np.arange(len(ids)), size)
        train = np.array([trains(i) for i in ids])
        token_c = c[codes]
        sums = (size, np.add.reduceat((token_c > 0).astype(np.int64), starts), np.add.reduceat(uni.base(c)[codes], starts))
        yield -1 - chunk % parts, chunk, pickle.dumps((ids, *sums))
        codes = codes.astype(np.int64)
        # the pairs after frequent words, in the order in which their counts came
        hot_of = hot_of.astype(np.int64)
        pairs, _ = _after_hot(ends, codes, hot_of, n_hot, train[doc])
        if len(pairs) != len(c2):
            raise RuntimeError("two reads of the documents differ; write them to a table first")
        # words by number: 0 is no word, 1 the starting context, and the words follow in order of gid
        by_gid = np.argsort(gid)
        rank = np.empty(len(gid), np.int64)
        rank[by_gid] = np.arange(2, len(gid) + 2)
        rank_gid = np.concatenate(([NO_WORD, START], gid[by_gid]))
        w, place = rank[codes], np.arange(len(codes)) - starts[doc]
        history = []
        for back in range(1, order):
            h = np.concatenate((np.zeros(back, np.int64), w[:-back]))[: len(w)]
            h[place == back - 1] = 1
            h[place < back - 1] = 0
            history.append(h)
        wide = len(gid) + 2
        by, at = _distinct([*history, w, doc], [wide] * order + [len(ids)])
        times = np.diff(np.append(at, len(by)))
        by = by[at]
        grams = [x[by] for x in (*history, w)]
        new = np.zeros(len(by), bool)
        new[:1] = True
        for g in grams:
            new[1:] |= g[1:] != g[:-1]
        first = np.flatnonzero(new)
        held_by, of = np.diff(np.append(first, len(by))), doc[by].astype(np.uint32)
        n = np.add.reduceat(times * train[of], first)
        grams = [rank_gid[g[first]] for g in grams]
        code = codes[by[first]]
        before = np.where(grams[0] == START, 0, hot_of[codes[np.maximum(by[first] - 1, 0)]])
        is_hot = before >= 0
        known = np.zeros(len(first), np.int64)
        known[is_hot] = c2[np.searchsorted(pairs, code[is_hot] * n_hot + before[is_hot])]
        # a frequent word's contexts are dealt by the word before it, or, where it starts the context, by the next word
        further = grams[1] if order > 2 else np.full(len(first), NO_WORD)
        salt = np.where(further != NO_WORD, further, grams[-1])
        bucket = ((_spread(grams[0]) + np.where(is_hot, _spread(salt) % SPREAD, 0).astype(np.uint64)) % np.uint64(parts)).astype(np.int64)
        # everything in order of the buckets once, so that a block is a slice of each array
        by = np.argsort(bucket.astype(np.uint32), kind="stable")
        bounds = np.searchsorted(bucket[by], np.arange(parts + 1))
        held_by, is_hot = held_by[by], is_hot[by]
        upto = np.concatenate(([0], np.cumsum(held_by)))
        take = np.repeat(first[by] - upto[:-1], held_by) + np.arange(int(upto[-1]))
        step = np.diff(grams[0][by], prepend=0)
        filled = bounds[:-1][bounds[:-1] < bounds[1:]]
        step[filled] = grams[0][by][filled]
        each = [_narrow(x) for x in (step, *(g[by] + 1 for g in grams[1:]), c[code[by]], n[by], before[by] + 1)]
        hot_upto, hot_known = np.concatenate(([0], np.cumsum(is_hot))), _narrow(known[by][is_hot])
        length, of, times = _narrow(held_by), _narrow(of[take]), _narrow(times[take])
        for k in range(parts):
            lo, hi = bounds[k], bounds[k + 1]
            if lo < hi:
                own, entries = slice(lo, hi), slice(upto[lo], upto[hi])
                yield k, chunk, pack(*(x[own] for x in each), hot_known[hot_upto[lo] : hot_upto[hi]], length[own], of[entries], times[entries], np.array([len(ids)], np.int64))

    def run(batches):
        for part in assembled(batches):
            for bucket, chunk, blob in done(*part):
                yield row_of(bucket, chunk, blob)

    return run


class _Merged:
    """The tables of all orders of one bucket, merged from the blocks of all chunks, whose words are numbered one up.

    ``grams``: the distinct n-grams, a column for each word back and the next word last; ``of``: which of them an entry of the
    blocks is; ``levels``: for order 2, 3, ... the rows (n-grams that have such a context), their entry in the table of that
    order, and of that table the number of the context, the training count, a row's n-gram and the number among frequent words.
    """

    def __init__(self, blocks: list[list[np.ndarray]], order: int):
        columns = [np.concatenate([b[k] for b in blocks]).astype(np.int64) for k in range(order)]
        c, n, before = (np.concatenate([b[order + k] for b in blocks]) for k in range(3))
        known = np.zeros(len(c), np.int64)
        known[before > 0] = np.concatenate([b[order + 3] for b in blocks])
        by, at = _distinct(columns, [int(x.max(initial=0)) + 1 for x in columns])
        self.of = np.empty(len(by), np.int64)
        count = np.diff(np.append(at, len(by)))
        self.of[by] = np.repeat(np.arange(len(at)), count)
        first = by[at]
        self.grams, self.c = [x[first] - 1 for x in columns], c[first].astype(np.int64)
        r, hot, known = np.add.reduceat(n[by].astype(np.int64), at) if len(at) else at, before[first].astype(np.int64) - 1, known[first]
        self.levels = []
        for level in range(2, order + 1):
            rows = np.flatnonzero(self.grams[level - 2] != NO_WORD)
            if level == order:
                # the n-grams themselves, which are distinct and in order
                entry, total, one = np.arange(len(rows)), r[rows], rows
            else:
                cols = [self.grams[k][rows] + 1 for k in range(level - 1)] + [self.grams[-1][rows]]
                by, at = _distinct(cols, [int(x.max(initial=0)) + 2 for x in cols])
                entry = np.empty(len(by), np.int64)
                entry[by] = np.repeat(np.arange(len(at)), np.diff(np.append(at, len(by))))
                total = np.add.reduceat(r[rows][by], at) if len(at) else at
                one = rows[by[at]]
            if level == 2:
                total = np.where(hot[one] >= 0, known[one], total)
            new = np.zeros(len(one), bool)
            new[:1] = True
            for k in range(level - 1):
                x = self.grams[k][one]
                new[1:] |= x[1:] != x[:-1]
            self.levels.append((rows, entry, np.cumsum(new) - 1, total, one, hot[one]))

    def counts(self) -> np.ndarray:
        """A row an order: how many of its n-grams were seen 0..CUT + 1 times; pairs after frequent words are counted elsewhere."""
        out = []
        for level, (_, _, _, r, _, hot) in enumerate(self.levels, 2):
            r = r[hot < 0] if level == 2 else r
            out.append(np.bincount(r[(r > 0) & (r <= CUT + 1)], minlength=CUT + 2))
        return np.array(out)

    def tables(self, uni: Unigrams, d: list[np.ndarray], hot_sums: np.ndarray):
        """For each order: (context numbers, counts, first rows, sums of the contexts, P of the table's n-grams)."""
        p = uni.p(self.c)
        for level, ((rows, entry, h, r, one, hot), own) in enumerate(zip(self.levels, d, strict=True), 2):
            lower = p[one]
            sums = context_sums(h, r, lower)
            if level == 2:
                first = np.flatnonzero(np.diff(h, prepend=-1))
                spread = hot[first] >= 0
                sums[spread] = hot_sums[hot[first][spread]]
            q = level_p(h, r, sums, lower, own)
            yield h, r, one, sums, q
            p = p.copy()
            p[rows] = q[entry]

    def logs(self, uni, d, hot_sums) -> np.ndarray:
        """log10 P of every distinct n-gram, from the longest context that it has."""
        p = uni.p(self.c)
        for (rows, entry, *_), (*_, q) in zip(self.levels, self.tables(uni, d, hot_sums), strict=True):
            p[rows] = q[entry]
        return np.log10(p)


def _blocks(rows):
    """(bucket, blocks) of a partition's rows, which come in order of bucket; rows with a negative one pass through."""
    for bucket, own in groupby(rows, key=lambda row: row["bucket"]):
        if bucket < 0:
            yield bucket, list(own)
            continue
        blocks = []
        for row in own:
            arrays = unpack(bytes(row["data"]))
            arrays[0] = np.cumsum(arrays[0], dtype=np.int64) + 1
            blocks.append((row["chunk"], arrays))
        yield bucket, blocks


def _count(order: int):
    """First job: counts of counts of every order."""

    def run(rows):
        n = np.zeros((order - 1, CUT + 2), np.int64)
        for bucket, blocks in _blocks(rows):
            if bucket >= 0:
                n += _Merged([a for _, a in blocks], order).counts()
        yield n

    return run


def _evaluate(order: int, uni: Unigrams, d: list[np.ndarray], hot_sums: np.ndarray):
    """Second job: every n-gram's log probability, added up by document of each chunk."""

    def emit(held):
        for chunk, part in held.items():
            docs = np.flatnonzero(part)
            yield Row(chunk=chunk, sums=False, data=bytearray(pack(docs.astype(np.uint32), part[docs])))

    def run(rows):
        held: dict[int, np.ndarray] = {}
        n_held = 0
        for bucket, blocks in _blocks(rows):
            if bucket < 0:
                for row in blocks:
                    yield Row(chunk=row["chunk"], sums=True, data=row["data"])
                continue
            m = _Merged([a for _, a in blocks], order)
            logs = m.logs(uni, d, hot_sums)[m.of]
            lo = 0
            for chunk, a in blocks:
                own, lo = logs[lo : lo + len(a[0])], lo + len(a[0])
                length, of, times, docs = a[-4:]
                part = np.bincount(of, np.repeat(own, length) * times, minlength=int(docs[0]))
                if chunk in held:
                    held[chunk] += part
                else:
                    held[chunk], n_held = part, n_held + len(part)
            if n_held > HELD_DOCS:
                yield from emit(held)
                held, n_held = {}, 0
        yield from emit(held)

    return run


def _finish(uni: Unigrams):
    """Rows in order of chunk, document sums first -> the report."""

    def done(head, score):
        ids, size, known, base = head
        n = len(ids)
        held = [i is not None and not trains(i) for i in ids]
        return pa.RecordBatch.from_arrays(
            [pa.array(ids, pa.int64()), pa.array(held), pa.array(size.astype(np.int64)), pa.array(known), pa.array(np.full(n, uni.tokens, np.int64)), pa.array(base), pa.array(score)],
            ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
        )

    def run(batches):
        now, head, score = None, None, None
        for b in batches:
            for r in b.to_pylist():
                if r["chunk"] != now:
                    if head:
                        yield done(head, score)
                    now, head = r["chunk"], pickle.loads(r["data"])
                    score = np.zeros(len(head[0]))
                else:
                    docs, part = unpack(r["data"])
                    score[docs] += part
        if head:
            yield done(head, score)

    return run


SCHEMA = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


class Model:
    """The fitted model of a corpus: discounts, sums of frequent contexts, and the shuffled blocks that the tables are made of."""

    def __init__(self, docs: DataFrame, order: int = ORDER):
        if order < 2:
            raise ValueError("the order is 2 or more")
        spark = docs.sparkSession
        self.spark, self.n, self.order = spark, n_buckets(docs), order
        self.width = int(spark.conf.get("spark.sql.shuffle.partitions"))
        rows = source(docs)
        hot = {w: k for k, w in enumerate(frequent_words(docs), 1)}
        n_hot = len(hot) + 1
        self.words = by_bucket(rows.mapInArrow(lean(_word_blocks(hot, self.n)), BLOCK))
        counted = materialize(self.words.mapInArrow(lean(_numbered(self.n, n_hot)), BLOCK))
        # one small row a task
        stats = sum((unpack(bytes(r["data"]))[0] for r in counted.where("bucket = -2").select("data").collect()), np.zeros(CUT + 3, np.int64))
        self.uni = Unigrams(np.concatenate(([0], stats[1 : CUT + 2])), int(stats[CUT + 2]), int(stats[0]))
        self.hot_sums, hot_counts = _hot_sums(counted, n_hot, self.uni)
        positions = rows.mapInArrow(lean(position_rows(keys, word_of, self.n, lambda words: _hot_numbers(words, hot).astype(np.int16))), BLOCK)
        blocks = by_chunk(counted.where("bucket >= 0"), positions).mapInArrow(lean(_deal(self.uni, BUCKETS * self.width, order, n_hot)), BLOCK)
        self.blocks = blocks.repartition(self.width, "bucket").sortWithinPartitions("bucket")
        # two jobs read the same shuffled blocks: an RDD keeps its shuffle, a plan would be run again
        self.dealt = self.blocks.rdd
        counts = sum(self.dealt.mapPartitions(_count(order)).collect(), np.zeros((order - 1, CUT + 2), np.int64))
        counts[0] += hot_counts
        self.d = [discounts(n) for n in counts]


def lm_report(docs: DataFrame, order: int = ORDER) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row."""
    m = Model(docs, order)
    parts = m.spark.createDataFrame(m.dealt.mapPartitions(_evaluate(order, m.uni, m.d, m.hot_sums)), "chunk long, sums boolean, data binary")
    return parts.repartition("chunk").sortWithinPartitions("chunk", F.col("sums").desc()).mapInArrow(lean(_finish(m.uni)), SCHEMA)


def _word_rows(uni: Unigrams, buckets: int):
    """Blocks of :func:`_word_blocks` in order of bucket -> the words that were seen, numbered as :func:`_numbered` does."""

    def run(batches):
        for bucket, rows in groupby((r for b in batches for r in b.to_pylist()), key=lambda r: r["bucket"]):
            table, codes, counts = Codes(), [], []
            for r in rows:
                sizes, text, count, *_ = unpack(r["data"])
                text, ends = text.tobytes(), np.cumsum(sizes).tolist()
                codes += [table[text[a:b]] for a, b in zip([0, *ends], ends)]
                counts.append(count)
            c = np.bincount(codes, np.concatenate(counts), len(table)).astype(np.int64)
            words, known = list(table), np.flatnonzero(c > 0)
            c = c[known]
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(c), bucket, np.int32)), pa.array(known * buckets + bucket + 1), pa.array([words[k].decode() for k in known.tolist()], pa.string()), pa.array(c), pa.array(np.log10(uni.p(c)))], ["bucket", "id", "word", "count", "log10_p"])

    return run


def _table_rows(m: Model, contexts: bool):
    order, uni, d, hot_sums = m.order, m.uni, m.d, m.hot_sums

    def run(batches):
        for bucket, blocks in _blocks(r for b in batches for r in b.to_pylist()):
            if bucket < 0:
                continue
            merged = _Merged([a for _, a in blocks], order)
            for level, (h, r, one, sums, p) in enumerate(merged.tables(uni, d, hot_sums), 2):
                if contexts:
                    alpha, _ = backoff(sums, d[level - 2])
                    at = np.flatnonzero(np.diff(h, prepend=-1))
                    keep = sums[:, 0] > 0
                    at, values = at[keep], [sums[keep, 0].astype(np.int64), np.log10(alpha[keep])]
                else:
                    at = np.flatnonzero(r > 0)
                    values = [merged.grams[-1][one[at]], r[at], np.log10(p[at])]
                context = np.stack([merged.grams[k][one[at]] for k in range(level - 1)][::-1], axis=1)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(at) + 1, dtype=np.int32) * (level - 1)), pa.array(context.ravel()))
                columns = [pa.array(np.full(len(at), level, np.int32)), pa.array(np.full(len(at), bucket, np.int32)), lists, *map(pa.array, values)]
                yield pa.RecordBatch.from_arrays(columns, ["level", "bucket", "context", *(("count", "log10_backoff") if contexts else ("word", "count", "log10_p"))])

    return run


def model_tables(docs: DataFrame, order: int = ORDER) -> dict[str, DataFrame]:
    """The model as tables, with a ``bucket`` to partition them by: ``words`` (id, word, count, log10_p), ``grams`` (level, context,
    word, count, log10_p) and ``backoffs`` (level, context, count, log10_backoff). A context is the numbers of its words, oldest
    first. The end token is the empty word; word 0 starts a text; a context that is not listed has backoff 1; the unknown word has
    the probability that words leave."""
    m = Model(docs, order)
    words = m.words.mapInArrow(lean(_word_rows(m.uni, m.n)), "bucket int, id long, word string, count long, log10_p double")
    grams = m.blocks.mapInArrow(lean(_table_rows(m, False)), "level int, bucket int, context array<long>, word long, count long, log10_p double")
    backoffs = m.blocks.mapInArrow(lean(_table_rows(m, True)), "level int, bucket int, context array<long>, count long, log10_backoff double")
    # what follows a frequent word is in several buckets
    return {"words": words, "grams": grams.dropDuplicates(["context", "word"]), "backoffs": backoffs.dropDuplicates(["context"])}


def write_tables(docs: DataFrame, path: str, order: int = ORDER) -> None:
    for name, df in model_tables(docs, order).items():
        df.write.mode("overwrite").partitionBy("bucket").parquet(f"{path}/{name}")
