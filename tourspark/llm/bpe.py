"""Byte-level BPE by corpus-level merge replay.

Three steps. Texts are cut into words, and every run of texts is written as numbers of words
in a list of the run's own distinct words. The list is dealt into buckets by the words'
checksums, all runs' words of a bucket meet, and each distinct word of the corpus is laid out
and replayed once: words make up one long list of
symbols, an inverted index leads from each mergeable pair, named by the rank of what it
makes, to the places where it stands, and merges are applied in rank order, each to all its
places at once; a merge touches only its two neighbours, whose new pairs enter the index. At
last the words' tokens go back to the runs, where every text is its words' tokens in a row.

A run ends after so many distinct words or characters, so what a task holds is bounded, and
a word that every text has comes once from each run. Buckets grow in number with the texts.
What is written and moved is compressed, a run's words of a bucket as one value. Decoding
goes from ids back to bytes.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import marshal
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import public_tokenizers
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark import TaskContext
from pyspark.sql import DataFrame

from tourspark.llm.rows import named, text_rows

RANKS = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
#: Code points and distinct words after which a run of texts ends, and words of one replay.
RUN_CHARS, RUN_WORDS, SLAB = 16_000_000, 300_000, 100_000
#: Texts for each bucket of words, and the fewest buckets.
BUCKET_TEXTS, LEAST_BUCKETS = 1024, 64
#: Rows of the first step: a text's words by their numbers (bucket TEXT), the buckets of a
#: run's words in order (DEALT), or a run's words of one bucket in order.
CUT = "run long, bucket int, id string, data binary"
TOKENS = "run long, bucket int, data binary"
TEXT, DEALT = -1, -2


@lru_cache(2)
def load(path: str = RANKS) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


@lru_cache(2)
def merges(path: str = RANKS) -> dict[int, int]:
    """Rank of what two neighbouring tokens make, by their ids in one number: every cut of a
    token into two tokens."""
    ranks = load(path)
    get, out = ranks.get, {}
    for piece, rank in ranks.items():
        for i in range(1, len(piece)):
            a, b = get(piece[:i]), get(piece[i:])
            if a is not None and b is not None:
                out[a << 32 | b] = rank
    return out


def replay(words: list[bytes], ranks: dict[bytes, int], pairs: dict[int, int]) -> list[list[int]]:
    """Token ids of each word. A word that is itself a token is that token."""
    token: list[int] = []
    left: list[int] = []
    right: list[int] = []
    first: list[int] = []
    places: dict[int, list[int]] = {}  # the inverted index: rank of a pair -> where it starts
    byte, get = [ranks[bytes([i])] for i in range(256)], pairs.get
    for w in words:
        n, whole = len(token), ranks.get(w)
        first.append(n if w else -1)
        if whole is not None:
            token.append(whole)
            left.append(-1)
            right.append(-1)
        elif w:
            own = [byte[c] for c in w]
            token += own
            left.append(-1)
            left += range(n, n + len(own) - 1)
            right += range(n + 1, n + len(own))
            right.append(-1)
            before = own[0]
            for i, t in enumerate(own[1:], n):
                r = get(before << 32 | t)
                if r is not None:
                    at = places.get(r)
                    if at is None:
                        places[r] = [i]
                    else:
                        at.append(i)
                before = t
    queue = list(places)
    heapq.heapify(queue)
    while queue:
        rank = heapq.heappop(queue)
        own = places.pop(rank)
        own.sort()
        for k, a in enumerate(own):
            b = right[a]
            # a place is stale where a merge has changed either token since
            if b < 0 or token[a] < 0 or get(token[a] << 32 | token[b]) != rank:
                continue
            token[a], token[b] = rank, -1
            c = right[a] = right[b]
            p, lower = left[a], False
            if c >= 0:
                left[c] = a
                r = get(rank << 32 | token[c])
                if r is not None:
                    at = places.get(r)
                    if at is None:
                        places[r] = [a]
                        heapq.heappush(queue, r)
                    else:
                        at.append(a)
                    lower = r < rank
            if p >= 0:
                r = get(token[p] << 32 | rank)
                if r is not None:
                    at = places.get(r)
                    if at is None:
                        places[r] = [p]
                        heapq.heappush(queue, r)
                    else:
                        at.append(p)
                    lower |= r < rank
            if lower and k + 1 < len(own):
                # an earlier merge has become possible: it goes first, then the rest of these
                if rank not in places:
                    places[rank] = []
                    heapq.heappush(queue, rank)
                places[rank] += own[k + 1 :]
                break
    out = []
    for at in first:
        ids = []
        while at >= 0:
            ids.append(token[at])
            at = right[at]
        out.append(ids)
    return out


class Coder:
    """Encodes and decodes in one process: words are cut, replayed together and joined."""

    def __init__(self, path: str = RANKS, pattern: str = public_tokenizers.PATTERN):
        self.ranks, self.pairs = load(path), merges(path)
        self.piece = {n: b for b, n in self.ranks.items()}
        self.split = regex.compile(pattern).findall

    def replay(self, words: list[str]) -> list[list[int]]:
        return replay([w.encode() for w in words], self.ranks, self.pairs)

    def encode(self, texts: list[str]) -> list[list[int]]:
        cut = [self.split(t) for t in texts]
        known = sorted({w for words in cut for w in words})
        ids = dict(zip(known, self.replay(known), strict=True))
        return [[i for w in words for i in ids[w]] for words in cut]

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.piece.__getitem__, ids))


@lru_cache(1)
def coder(path: str) -> Coder:
    """One for each worker process: its tables are made once."""
    return Coder(path)


def squeezed(numbers: np.ndarray) -> bytes:
    """Numbers below 2**32, compressed: their bytes by place, as most of the high ones are 0."""
    return zlib.compress(np.ascontiguousarray(numbers.astype("<u4").view(np.uint8).reshape(-1, 4).T).tobytes(), 1)


def numbers_in(data: bytes) -> np.ndarray:
    raw = np.frombuffer(zlib.decompress(data), np.uint8)
    return np.ascontiguousarray(raw.reshape(4, -1).T).view("<u4").ravel()


def _cut(batches: Iterator[pd.DataFrame], path: str, most_chars: int, most_words: int, buckets: int) -> Iterator[pd.DataFrame]:
    split = coder(path).split
    run = TaskContext.get().partitionId() << 40
    numbers: dict[str, int] = {}
    chars = 0

    def word_lists() -> pd.DataFrame:
        words = list(numbers)
        dealt = np.fromiter((zlib.crc32(w.encode()) % buckets for w in words), np.int64, len(words))
        order = np.argsort(dealt, kind="stable")
        used, first = np.unique(dealt[order], return_index=True)
        lists = [[words[k] for k in own] for own in np.split(order, first[1:])]
        data = [squeezed(dealt), *(zlib.compress(marshal.dumps(own), 1) for own in lists)]
        return pd.DataFrame({"run": run, "bucket": np.r_[DEALT, used].astype(np.int32), "id": None, "data": data})

    for rows in batches:
        ids, held = [], []
        for i, t in zip(rows["id"], rows["t"], strict=True):
            own = [numbers.setdefault(w, len(numbers)) for w in split(t)]
            ids.append(i)
            held.append(squeezed(np.array(own, np.uint32)))
            chars += len(t)
            if chars >= most_chars or len(numbers) >= most_words:
                yield pd.DataFrame({"run": run, "bucket": TEXT, "id": ids, "data": held})
                yield word_lists()
                ids, held, chars, run = [], [], 0, run + 1
                numbers.clear()
        if ids:
            yield pd.DataFrame({"run": run, "bucket": TEXT, "id": ids, "data": held})
    if numbers:
        yield word_lists()


def _replayed(batches: Iterator[pd.DataFrame], path: str, slab: int) -> Iterator[pd.DataFrame]:
    """Rows sorted by word: each distinct word is replayed once, with the others of a slab."""
    own, last, last_ids = coder(path), None, b""
    for rows in batches:
        word = rows["word"].to_numpy()
        fresh = np.r_[word[:1] != last, word[1:] != word[:-1]]
        new = word[fresh].tolist()
        made = [last_ids] if not len(fresh) or not fresh[0] else []
        for at in range(0, len(new), slab):
            made += [np.array(ids, "<i4").tobytes() for ids in own.replay(new[at : at + slab])]
        place = np.cumsum(fresh) - 1 + (len(made) - len(new))
        if len(word):
            last, last_ids = word[-1], made[place[-1]]
            yield pd.DataFrame({"run": rows["run"], "n": rows["n"], "ids": np.array(made, object)[place]})


def _squeezed_tokens(ids: list[bytes]) -> bytes:
    sizes = np.fromiter(map(len, ids), np.int64, len(ids)) // 4
    return marshal.dumps((squeezed(sizes), squeezed(np.frombuffer(b"".join(ids), "<i4"))))


def _tokens_in(data: bytes) -> list[bytes]:
    sizes, flat = map(numbers_in, marshal.loads(data))
    ends, body = (np.cumsum(sizes, dtype=np.int64) * 4).tolist(), flat.tobytes()
    return [body[a:b] for a, b in zip([0, *ends], ends, strict=False)]


def _bucket_tokens(rows: pd.DataFrame, path: str, slab: int) -> pd.DataFrame:
    """The tokens of one bucket's words, for each run in the order of its list."""
    lists = [marshal.loads(zlib.decompress(d)) for d in rows["data"]]
    words = np.array([w for own in lists for w in own], object)
    order = np.array(sorted(range(len(words)), key=words.__getitem__))
    ids = np.empty(len(words), object)
    for made in _replayed(iter([pd.DataFrame({"run": 0, "n": order, "word": words[order]})]), path, slab):
        ids[made["n"].to_numpy()] = made["ids"].to_numpy()
    ends = np.cumsum([len(own) for own in lists])
    data = [_squeezed_tokens(own.tolist()) for own in np.split(ids, ends[:-1])]
    return pd.DataFrame({"run": rows["run"], "bucket": rows["bucket"], "data": data})


def cut_words(docs: DataFrame, id_col: str, text: str, path: str = RANKS, most_chars: int = RUN_CHARS, most_words: int = RUN_WORDS) -> DataFrame:
    """Rows of CUT: every text as numbers of its run's words, and each run's words; a run's
    rows are in one task. Its two readers share that exchange, as neither has a filter that the
    engine would push below it; so texts are moved once and written nowhere else.

    A task that is run again must find its rows in the same order, as those of a table are.
    """
    rows = text_rows(docs, id_col, text, empty=True)
    buckets = max(LEAST_BUCKETS, 1 << (docs.count() // BUCKET_TEXTS).bit_length())
    return rows.mapInPandas(lambda b: _cut(b, path, most_chars, most_words, buckets), CUT).repartition("run")


def _words_alone(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        yield b.filter(pc.greater_equal(b["bucket"], 0))


def word_tokens(cut: DataFrame, path: str = RANKS, slab: int = SLAB) -> DataFrame:
    """(run, bucket, data): the tokens of each run's words. All words of a bucket are in one
    group, and each distinct one is replayed once; a word has at most a row a run."""
    words = cut.mapInArrow(_words_alone, CUT).select("run", "bucket", "data")
    return words.groupBy("bucket").applyInPandas(lambda rows: _bucket_tokens(rows, path, slab), TOKENS)


def _in_order(dealt: pd.Series, tokens: pd.DataFrame) -> list[bytes]:
    """The tokens of a run's words by their numbers; a run without words has no row ``dealt``."""
    if not len(dealt):
        return []
    at = numbers_in(dealt.iloc[0])
    tokens = tokens.sort_values("bucket")
    out = np.empty(len(at), object)
    # words go by bucket, and inside one by number, as they were dealt
    out[np.argsort(at, kind="stable")] = [i for d in tokens["data"] for i in _tokens_in(d)]
    return out.tolist()


def _joined(docs: DataFrame, id_col: str, text: str, path: str, kind: str, of_text, most_chars: int, most_words: int) -> DataFrame:
    """``of_text`` of every text, given the numbers of its words and the tokens of each."""
    cut = cut_words(docs, id_col, text, path, most_chars, most_words)

    def meet(texts: pd.DataFrame, tokens: pd.DataFrame) -> pd.DataFrame:
        ids = _in_order(texts["data"][texts["bucket"] == DEALT], tokens)
        texts = texts[texts["bucket"] == TEXT]
        return of_text(coder(path), texts["id"].tolist(), (numbers_in(w).tolist() for w in texts["data"]), ids)

    made = cut.groupBy("run").cogroup(word_tokens(cut, path).groupBy("run")).applyInPandas(meet, kind)
    return named(made, docs, id_col)


def _digests(own: Coder, ids: list, texts: Iterator[list[int]], tokens: list[bytes]) -> pd.DataFrame:
    lists = [np.frombuffer(t, "<i4").tolist() for t in tokens]
    text_of = [",".join(map(str, x)) for x in lists].__getitem__
    size_of, back_of, sha = [len(x) for x in lists].__getitem__, [own.decode(x) for x in lists].__getitem__, hashlib.sha256
    rows = [(i, sum(map(size_of, w)), sha(",".join(map(text_of, w)).encode()).hexdigest(), sha(b"".join(map(back_of, w))).hexdigest()) for i, w in zip(ids, texts, strict=True)]
    return pd.DataFrame(rows, columns=["id", "n_tokens", "ids_sha256", "decoded_sha256"])


def _lists(own: Coder, ids: list, texts: Iterator[list[int]], tokens: list[bytes]) -> pd.DataFrame:
    return pd.DataFrame({"id": ids, "ids": [np.frombuffer(b"".join(map(tokens.__getitem__, w)), "<i4") for w in texts]})


def code(docs: DataFrame, id_col: str = "doc_id", text: str = "text", path: str = RANKS, most_chars: int = RUN_CHARS, most_words: int = RUN_WORDS) -> DataFrame:
    """(id, n_tokens, ids_sha256, decoded_sha256) of every row; null texts count as empty and
    have no tokens. Texts are read whole, however long; a long one ends its run. Repeated rows
    come back repeated, an empty table empty; other columns are ignored."""
    return _joined(docs, id_col, text, path, "id string, n_tokens long, ids_sha256 string, decoded_sha256 string", _digests, most_chars, most_words)


def encode_documents(docs: DataFrame, id_col: str = "doc_id", text: str = "text", path: str = RANKS, most_chars: int = RUN_CHARS, most_words: int = RUN_WORDS) -> DataFrame:
    """(id, ids array<int>) of every row: the ids themselves, as in ``code``."""
    return _joined(docs, id_col, text, path, "id string, ids array<int>", _lists, most_chars, most_words)
