"""Byte-level BPE encoding by a global shuffle of distinct words, and decoding by the token-byte table.

A word is a maximal run of white space with the run of other characters after it, cut so that no match of the
tokenizer's pattern crosses a cut; each word's tokens therefore depend on the word alone. Words are taken out of the
documents with their positions, each distinct word of the corpus is encoded once after a shuffle by word, the ids go back
to the texts that hold it and are put together again by position (:mod:`pointloom.llm.wordshuffle`).

Defined cases: null and empty texts have no tokens (digests of the empty string); a null doc_id and repeated rows are
kept as they are; special tokens' strings are ordinary text; an empty table gives an empty result; extra columns
are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from pointloom.llm.common import lean
from pointloom.llm.wordshuffle import BLOCK, assembled, by_bucket, by_chunk, merge_blocks, n_buckets, pack, position_rows, source, unpack, word_blocks

#: White space as the tokenizer's pattern sees it: Python's, without the separators 1C-1F.
_SPACE = "[^\\S\\x1c-\\x1f]"
_WORD = re.compile(f"{_SPACE}*[\\S\\x1c-\\x1f]+|{_SPACE}+")
_DOUBLE = re.compile(f"{_SPACE} ")


def tokenizer(ranks: bytes, pattern: str):
    import tiktoken

    table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, ranks.splitlines())}
    return tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=table, special_tokens={}), table


def word_keys(text: str) -> list:
    """Keys of the text's words in order; :func:`word_of` gives the word back.

    ``x`` stands for the word space + x, ``newline x`` for itself, a 1-tuple for a word that starts otherwise. Where a space
    or a newline follows white space, the words are found by a pattern, else by splitting at spaces.
    """
    if not text:
        return []
    line = text.replace("\n", " \n")
    if any(x in line for x in ("  ", "\n ", "\t ", "\r ", "\x0b ", "\x0c ")) or not line.isascii() and _DOUBLE.search(line):
        return [w[1:] if w[0] == " " and w[1:2] != "\n" else w if w[0] == "\n" else (w,) for w in _WORD.findall(text)]
    keys = line.split(" ")
    keys[0] = (keys[0],)
    return keys


def word_of(key) -> bytes:
    return (key[0] if type(key) is tuple else key if key[:1] == "\n" else " " + key).encode()


def _encoder(ranks, pattern):
    """Each distinct word of a bucket is encoded once; every block gets its words' ids."""
    held = []

    def answer(bucket, words, own):
        if not held:
            held.append(tokenizer(ranks.value, pattern)[0])
        ids = [held[0].encode_ordinary(w.decode()) for w in words]
        size = np.fromiter(map(len, ids), np.int64, len(ids))
        flat, start = np.fromiter(chain.from_iterable(ids), np.int64, int(size.sum())), np.cumsum(size) - size
        for codes in own:
            yield pack(size[codes].astype(np.uint32), flat[_ranges(start[codes], size[codes])].astype(np.uint32))

    return merge_blocks(answer)


def _ranges(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """The numbers start, start + 1, ... of each range, one range after the other."""
    return np.repeat(start - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))


def _assembler(finish, step: int = 512):
    """Task function: a chunk's positions and its words' ids -> finish(doc ids, token arrays), some documents at a time."""

    def run(batches):
        for _, ids, ends, codes, n_words, answers in assembled(batches):
            parts = [unpack(x) for x in answers]
            size = np.concatenate([p[0] for p in parts]).astype(np.int64) if parts else np.zeros(0, np.int64)
            flat = np.concatenate([p[1] for p in parts]) if parts else np.zeros(0, np.uint32)
            if len(size) != n_words:
                raise RuntimeError("two reads of the documents differ; write them to a table first")
            start = np.cumsum(size) - size
            for lo in range(0, len(ids), step):
                hi = min(lo + step, len(ids))
                first = int(ends[lo - 1]) if lo else 0
                own = codes[first : int(ends[hi - 1])]
                tokens = flat[_ranges(start[own], size[own])]
                upto = np.concatenate(([0], np.cumsum(size[own])))
                cuts = [0, *upto[ends[lo:hi] - first].tolist()]
                yield finish(ids[lo:hi], [tokens[x:y] for x, y in zip(cuts[:-1], cuts[1:], strict=True)])

    return run


def _assembled(docs: DataFrame, ranks, pattern: str, finish, schema: str) -> DataFrame:
    rows, n = source(docs), n_buckets(docs)
    blocks = by_bucket(rows.mapInArrow(lean(word_blocks(word_keys, word_of, n)), BLOCK))
    answers = blocks.mapInArrow(lean(_encoder(ranks, pattern)), BLOCK)
    positions = rows.mapInArrow(lean(position_rows(word_keys, word_of, n)), BLOCK)
    return by_chunk(answers, positions).mapInArrow(lean(_assembler(finish)), schema)


def _sent(docs: DataFrame, path: str):
    """The vocabulary file's bytes; its size does not depend on the documents."""
    with open(path, "rb") as f:
        return docs.sparkSession.sparkContext.broadcast(f.read())


def encode(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, ids (array of token ids) of every row."""

    def finish(ids, tokens):
        return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([t.astype(np.int32) for t in tokens], pa.list_(pa.int32()))], ["doc_id", "ids"])

    return _assembled(docs, _sent(docs, path), pattern, finish, "doc_id long, ids array<int>")


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """doc_id, bytes: each id is looked up in the token-byte table, which has as many rows as the vocabulary."""
    ranks = _sent(encoded, path)

    def run(batches):
        table = {int(b): base64.b64decode(a) for a, b in map(bytes.split, ranks.value.splitlines())}
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([b"".join(map(table.__getitem__, x.as_py() or ())) for x in b.column(1)], pa.binary())], ["doc_id", "bytes"])

    return encoded.select("doc_id", "ids").mapInArrow(lean(run), "doc_id long, bytes binary")


def bpe_report(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, n_tokens, and digests of the ids and of what they decode to."""
    ranks = _sent(docs, path)
    held = {}

    def finish(ids, tokens):
        if not held:
            held["bytes"] = {int(b): base64.b64decode(a) for a, b in map(bytes.split, ranks.value.splitlines())}
            held["text"] = {k: b"%d" % k for k in held["bytes"]}
        out = [t.tolist() for t in tokens]
        sha = [[hashlib.sha256(gap.join(map(held[kind].__getitem__, t))).hexdigest() for t in out] for kind, gap in (("text", b" "), ("bytes", b""))]
        return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([len(t) for t in out], pa.int64()), pa.array(sha[0]), pa.array(sha[1])], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return _assembled(docs, ranks, pattern, finish, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
