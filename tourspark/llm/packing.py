"""Cost-balanced packing of token ids into sequences of fixed capacity.

The work of a sequence is estimated as a linear part for its tokens plus a quadratic part
for attention inside each of its pieces. Documents are taken in descending order of their
estimated cost; each goes to the sequence of lowest cost so far that has room, and what
doesn't fit is cut off and goes to the next lowest. As many full sequences are opened as the
tokens fill; what is over makes up sequences whose lengths are powers of two, which need no
padding, so no place stays empty.

A run packs neighbouring documents of one task, up to ``run_tokens`` tokens: nothing is
shuffled, memory is bounded, and a run has a few short sequences at its end.
"""

from __future__ import annotations

import heapq
import json
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import public_tokenizers
import tiktoken
from pyspark import TaskContext
from pyspark.sql import DataFrame

from tourspark.llm.rows import named, text_rows

VOCABULARY = public_tokenizers.path("byte_bpe_50k.json")
LENGTH, END = 1024, 0


@lru_cache(2)
def encoder(path: str = VOCABULARY) -> tiktoken.Encoding:
    """The byte-level vocabulary of a tokenizer file. Its ids rise with the merges' ranks, so
    they serve as ranks; tests compare the ids with the file's own library. The file's added
    tokens are special ones here."""
    with open(path, encoding="utf-8") as f:
        read = json.load(f)
    vocabulary, added = read["model"]["vocab"], read.get("added_tokens") or []
    if any(t["single_word"] or t["lstrip"] or t["rstrip"] for t in added):
        raise ValueError("added tokens that take in or need text beside them are not supported")
    # the public byte-level alphabet: printable bytes stand for themselves, others from 256 on
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    byte_of = {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in plain)}
    ranks = {bytes(byte_of[c] for c in piece): n for piece, n in vocabulary.items() if not piece.startswith("<|")}
    special = {t["content"]: t["id"] for t in added}
    return tiktoken.Encoding("bytes", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=special)


def ids_of(text: str, path: str = VOCABULARY) -> list[int]:
    """The ids that the file's own library gives a text: its added tokens are found anywhere,
    and what lies between two of them is encoded by itself."""
    return encoder(path).encode(text, allowed_special="all")


def balanced(lengths: list[int], length: int = LENGTH, linear: float = 1.0, quadratic: float = 1.0 / LENGTH) -> Iterator[tuple[int, int, int, int, int]]:
    """(document, start, size, sequence, offset) of every piece. Ties: the earlier document,
    the smaller sequence. Pieces of a document follow one another."""
    total = sum(lengths)
    full, over = divmod(total, length)
    # the rest in binary: sequences of lengths that are powers of two, the longest first
    room = [length] * full + [1 << bit for bit in range(over.bit_length() - 1, -1, -1) if over >> bit & 1]
    open_ones = [(0.0, s) for s in range(len(room))]
    used = [0] * len(room)
    order = sorted(range(len(lengths)), key=lambda d: (-(linear * lengths[d] + quadratic * lengths[d] ** 2), d))
    for d in order:
        start, left = 0, lengths[d]
        while left:
            cost, s = heapq.heappop(open_ones)
            size = min(left, room[s] - used[s])
            yield d, start, size, s, used[s]
            used[s] += size
            start += size
            left -= size
            if used[s] < room[s]:
                heapq.heappush(open_ones, (cost + linear * size + quadratic * size * size, s))


def _pieces(batches: Iterator[pd.DataFrame], path: str, length: int, run_tokens: int) -> Iterator[pd.DataFrame]:
    part, sequence = TaskContext.get().partitionId(), 0
    held: list[tuple[object, np.ndarray]] = []
    tokens = 0

    def packed() -> pd.DataFrame:
        nonlocal sequence
        rows, highest = [], -1
        for d, start, size, s, offset in balanced([len(ids) for _, ids in held], length):
            own = held[d][1]
            rows.append((held[d][0], start, size, zlib.crc32(own[start : start + size]), len(own), (part << 40) + sequence + s, offset))
            highest = max(highest, s)
        sequence += highest + 1
        return pd.DataFrame(rows, columns=["id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

    for rows in batches:
        for i, t in zip(rows["id"].tolist(), rows["t"], strict=True):
            held.append((i, np.array([*ids_of(t or "", path), END], "<u4")))
            tokens += len(held[-1][1])
            if tokens >= run_tokens:
                yield packed()
                held, tokens = [], 0
    if held:
        yield packed()


def pack(docs: DataFrame, id_col: str = "doc_id", text: str = "text", path: str = VOCABULARY, length: int = LENGTH, run_tokens: int = 4_000_000) -> DataFrame:
    """The pieces of every row: id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    A row's ids are its text's, then 0. Null and empty texts have that one id; texts are read
    whole, and a long one has many pieces. Within a run ties go to the earlier row and the
    smaller sequence; runs follow the order in which a task reads its rows. Sequence ids hold
    the task in their upper bits, which a repeated task gets again. Repeated rows are packed
    each; an empty table gives no pieces; other columns are ignored.
    """
    made = text_rows(docs, id_col, text).mapInPandas(
        lambda b: _pieces(b, path, length, run_tokens),
        "id string, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long",
    )
    return named(made, docs, id_col)
