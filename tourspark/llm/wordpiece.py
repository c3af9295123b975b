"""Token counts by a linear longest-match automaton.

Greedy word pieces take, at each place of a word, the longest piece of the vocabulary. The
pieces form a trie. Every node has a failure link: where the walk goes on when the node has
no child for the next letter, together with how many tokens are then settled, worked out
beforehand. One pass over a word's letters so gives its number of tokens in linear time,
without cutting a single piece.

Words are runs of non-space characters with the vocabulary's mark of a word's start in
front. A word that the pieces can't cover is one unknown token.
"""

from __future__ import annotations

from collections import Counter, deque
from collections.abc import Iterator
from functools import lru_cache

import pandas as pd
import public_tokenizers
import sentencepiece
from pyspark.sql import DataFrame

from tourspark.llm.rows import named, text_rows

MODEL = public_tokenizers.path("piece_bpe_32k.model")
START = "▁"
#: Most bytes of words whose sizes a task remembers.
MOST_CACHED = 64 << 20


class Automaton:
    """Trie with failure links. ``pops[node]``: tokens settled when its link is taken;
    ``link[node]`` is -1 where no cover is left."""

    def __init__(self, pieces: list[str]):
        self.next: list[dict[str, int]] = [{}]
        end = [False]
        for p in pieces:
            at = 0
            for c in p:
                to = self.next[at].get(c)
                if to is None:
                    to = self.next[at][c] = len(self.next)
                    self.next.append({})
                    end.append(False)
                at = to
            end[at] = bool(p)
        self.link, self.pops = [-1] * len(self.next), [0] * len(self.next)
        queue = deque([0])
        while queue:
            u = queue.popleft()
            for c, v in self.next[u].items():
                queue.append(v)
                if end[v]:  # the whole node is a piece
                    self.link[v], self.pops[v] = 0, 1
                    continue
                # the longest piece inside the parent is settled; its rest leads on by c
                at, popped = self.link[u], self.pops[u]
                while at >= 0 and c not in self.next[at]:
                    popped += self.pops[at]
                    at = self.link[at]
                if at >= 0:
                    self.link[v], self.pops[v] = self.next[at][c], popped

    def count(self, word: str) -> int:
        """Number of pieces of the greedy cover, or -1 without one."""
        at, n = 0, 0
        steps, link, pops = self.next, self.link, self.pops
        for c in word:
            to = steps[at].get(c)
            while to is None:
                n += pops[at]
                at = link[at]
                if at < 0:
                    return -1
                to = steps[at].get(c)
            at = to
        while at > 0:
            n += pops[at]
            at = link[at]
        return n if at == 0 else -1


@lru_cache(2)
def automaton(path: str = MODEL) -> Automaton:
    """Of a vocabulary file's plain pieces; control, unknown and byte pieces are left out."""
    model = sentencepiece.SentencePieceProcessor(model_file=path)
    ids = range(model.get_piece_size())
    return Automaton([model.id_to_piece(i) for i in ids if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i))])


def _run(batches: Iterator[pd.DataFrame], path: str) -> Iterator[pd.DataFrame]:
    auto, known = automaton(path), {}
    for rows in batches:
        made = []
        for t in rows["t"]:
            tokens = words = unknown = 0
            for w, n in Counter(t.split()).items():
                size = known.get(w)
                if size is None:
                    size = known[w] = auto.count(START + w)
                words += n
                if size < 0:
                    unknown += n
                    tokens += n
                else:
                    tokens += n * size
            made.append((words, tokens, unknown))
        if sum(map(len, known)) + 120 * len(known) > MOST_CACHED:
            known.clear()
        yield pd.concat([rows.drop(columns="t"), pd.DataFrame(made, columns=["n_words", "n_tokens", "n_unknown"], index=rows.index)], axis=1)


def token_counts(docs: DataFrame, id_col: str = "doc_id", text: str = "text", path: str = MODEL) -> DataFrame:
    """(id, n_words, n_tokens, n_unknown) of every row. Null texts count as empty: all 0.
    Texts and words are read whole, however long, in one pass. Repeated rows come back
    repeated, an empty table empty; other columns are ignored."""
    rows = text_rows(docs, id_col, text, empty=True)
    return named(rows.mapInPandas(lambda b: _run(b, path), "id string, n_words long, n_tokens long, n_unknown long"), docs, id_col)
