"""SimHash near-duplicates by pigeonring filtering.

For a budget of t bits the 64 bits of a fingerprint lie on a ring of m = t + 1 segments. If
two fingerprints differ in at most t bits, then from some segment on, every chain of l
consecutive segments differs in at most floor(l * t / m) = l - 1 bits in all. So the first
segment agrees, and of the second at least one half does: that is the join key (m starts, 2
halves; 24 bits for t = 3). Pairs that meet under a key must then hold the chain length by
length; what breaks a budget on the way is dropped there, and only pairs that hold all the
shorter chains come to the last one, which is the whole ring and so the full distance.

Equal fingerprints are one node, so copies never form pairs. Fingerprints that share a key
are compared in tiles; a key with many fingerprints is dealt over many cells, one for each
pair of its tiles. A cell gives a spanning forest of the links it finds, not the links.

With ``views`` above 1 a text has that many fingerprints, from independent mixes of the same
shingle hashes; texts link where any of their fingerprints do. Near copies of moderate
similarity, whose distance in one view is often above the budget, so meet in another, while
the budget, which keeps unlike texts apart, stays small.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tourspark.llm.rows import join_spread, text_rows
from tourspark.plans.components import min_label_components
from tourspark.session import stage

# Separators of words, the hash seed, and the upper-case letters that fold.
WORD = re.compile(r"[^\x20\x09-\x0D]+")
SEED = 42
FOLD = {c: c + 32 for c in range(65, 91)}

SLICE = 1 << 15
#: The most bits of a budget: with more, the agreeing segment gets too short to be a key.
MOST_BITS = 7


def _mixed(hashes: np.ndarray, view: int) -> np.ndarray:
    """Hashes for another view: a bijection of 64-bit numbers for each, none for view 0."""
    if not view:
        return hashes
    x = hashes ^ np.uint64(view * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
    for shift, factor in ((33, 0xFF51AFD7ED558CCD), (33, 0xC4CEB9FE1A85EC53)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
    return x ^ (x >> np.uint64(33))


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """SimHash over all word shingles, repeats included; 0 for a text without words."""
    return fingerprint_views(text, shingle, 1)[0]


def shingle_hashes(text: str | None, shingle: int) -> np.ndarray:
    """Hashes of all word shingles, repeats included; a shorter text is one shingle."""
    words = WORD.findall(text.translate(FOLD)) if text else []
    if not words:
        return np.zeros(0, np.uint64)
    coded, digest = [w.encode() for w in words], xxhash.xxh64_intdigest
    if len(coded) <= shingle:
        return np.array([digest(b" ".join(coded), SEED)], np.uint64)
    line, ends, at = b" ".join(coded), [], -1
    for w in coded:
        at += len(w) + 1
        ends.append(at)
    starts = [0, *[e + 1 for e in ends]]
    return np.array([digest(line[a:b], SEED) for a, b in zip(starts, ends[shingle - 1 :], strict=False)], np.uint64)


def fingerprint_of(hashes: np.ndarray, views: int = 1) -> list[int]:
    """The fingerprints of shingle hashes in all views: a bit is 1 if over half have it."""
    ones = np.zeros((views, 64), np.int64)
    for at in range(0, len(hashes), SLICE):
        part = hashes[at : at + SLICE]
        for view in range(views):
            ones[view] += np.unpackbits(_mixed(part, view).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return np.packbits(2 * ones > len(hashes), axis=1, bitorder="little").view(np.uint64).ravel().tolist()


def fingerprint_views(text: str | None, shingle: int, views: int) -> list[int]:
    """The fingerprints of a text in all views."""
    return fingerprint_of(shingle_hashes(text, shingle), views)


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text: str = "text", shingle: int = 3, views: int = 1) -> DataFrame:
    """(id as text, fp, others): the fingerprint's 64 bits as a signed long, and those of
    further views. Null text counts as empty."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for rows in batches:
            made = np.array([fingerprint_views(t, shingle, views) for t in rows["t"]], np.uint64).view(np.int64).reshape(-1, views)
            yield pd.DataFrame({"id": rows["id"], "fp": made[:, 0], "others": list(made[:, 1:])})

    return text_rows(docs, id_col, text).mapInPandas(run, "id string, fp long, others array<long>")


def segments(budget: int) -> list[tuple[int, int]]:
    """(shift, width) of the budget + 1 segments of the ring."""
    cut = [64 * i // (budget + 1) for i in range(budget + 2)]
    return [(a, b - a) for a, b in zip(cut, cut[1:], strict=False)]


def _bits(fp: np.ndarray, shift: int, width: int) -> np.ndarray:
    return (fp >> np.uint64(shift)) & np.uint64((1 << width) - 1)


def _keys(fp: np.ndarray, budget: int) -> list[np.ndarray]:
    """Join keys of each fingerprint; a key's upper half says from which segment it starts.

    A budget of 0 has one segment, all 64 bits, so the digest of the whole is the key.
    """
    ring = segments(budget)
    if len(ring) == 1:
        return [(fp % np.uint64(0xFFFFFFFB)).astype(np.int64)]
    out = []
    for i, (shift, width) in enumerate(ring):
        at, size = ring[(i + 1) % len(ring)]
        for half, (s, w) in enumerate(((at, size // 2), (at + size // 2, size - size // 2))):
            w = min(w, 16)  # fewer bits than agree make a looser key, not a wrong one
            key = np.uint64(i << 33 | half << 32) | _bits(fp, shift, min(width, 16)) << np.uint64(w) | _bits(fp, s, w)
            out.append(key.astype(np.int64))
    return out


def chain_survivors(x: np.ndarray, start: np.ndarray | int, budget: int, dropped: np.ndarray | None = None) -> np.ndarray:
    """Which differences ``x`` keep every chain budget from segment ``start`` on.

    Chains grow segment by segment, and what breaks a budget isn't looked at again; the chain
    of all segments is the full distance. ``dropped[l - 1]`` counts what a chain of length l
    has sorted out.
    """
    ring = segments(budget)
    mask = np.array([((1 << w) - 1) << s for s, w in ring], np.uint64)
    live, total = None, 0
    for step in range(len(ring)):
        at = (start + step) % len(ring)
        if live is None:
            total = np.bitwise_count(x & mask[at]).astype(np.int64)
        else:
            total = total + np.bitwise_count(x[live] & mask[at if isinstance(at, int) else at[live]])
        ok = total * len(ring) <= (step + 1) * budget
        if dropped is not None:
            dropped[step] += len(ok) - int(ok.sum())
        live, total = np.flatnonzero(ok) if live is None else live[ok], total[ok]
    return live


class _Forest:
    """Union-find over the fingerprints of a cell: says which links join something new."""

    def __init__(self) -> None:
        self.up: dict[int, int] = {}

    def root(self, a: int) -> int:
        up = self.up
        while (b := up.get(a, a)) != a:
            up[a] = up.get(b, b)
            a = b
        return a

    def join(self, a: int, b: int) -> bool:
        a, b = self.root(a), self.root(b)
        if a == b:
            return False
        self.up[max(a, b)] = min(a, b)
        return True


def _start(key: np.ndarray) -> np.ndarray:
    return key >> 33 & 7


def _linked(key: np.ndarray, fp: np.ndarray, node: np.ndarray, budget: int, dropped: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Spanning links of rows sorted by key: only rows with one key are compared."""
    out, forest = [], _Forest()
    edge = np.flatnonzero(np.r_[True, key[1:] != key[:-1], True])
    size = np.diff(edge)
    group = np.repeat(np.arange(len(size)), size)
    start = _start(key)
    small = np.flatnonzero(size[group] <= 64)
    # small groups together: each row against the one `shift` places on
    for shift in range(1, int(size[size <= 64].max(initial=1))):
        i = small[small + shift < len(key)]
        i = i[group[i + shift] == group[i]]
        if not len(i):
            continue
        hit = i[chain_survivors(fp[i] ^ fp[i + shift], start[i], budget, dropped)]
        out += [(a, b) for a, b in zip(node[hit].tolist(), node[hit + shift].tolist(), strict=True) if forest.join(a, b)]
    for g in np.flatnonzero(size > 64):
        own = slice(edge[g], edge[g + 1])
        out += _tile((fp[own], node[own]), (fp[own], node[own]), int(start[edge[g]]), budget, forest, dropped)
    return out


def _tile(left: tuple[np.ndarray, np.ndarray], right: tuple[np.ndarray, np.ndarray], start: int, budget: int, forest: _Forest, dropped: np.ndarray | None = None, rows: int = 256) -> list[tuple[int, int]]:
    """Spanning links between two lists (fingerprints, nodes) under one key: a link between
    nodes that earlier ones have connected gives no row."""
    out = []
    for at in range(0, len(left[0]), rows):
        fp, node = left[0][at : at + rows], left[1][at : at + rows]
        hit = chain_survivors((fp[:, None] ^ right[0][None, :]).ravel(), start, budget, dropped)
        i, j = np.divmod(hit, max(1, len(right[0])))
        for a, b in zip(node[i].tolist(), right[1][j].tolist(), strict=True):
            if a != b and forest.join(a, b):
                out.append((a, b))
    return out


def links(views: DataFrame, budget: int = 3, tile: int = 2048) -> DataFrame:
    """(a, b): links among nodes that span every linked group.

    ``views``: rows (node, view, fp) without repeats. Any two nodes whose fingerprints of one
    view are within ``budget`` bits, 7 at most, are connected by the rows returned.
    """
    if not 0 <= budget <= MOST_BITS:
        raise ValueError(f"budgets go from 0 to {MOST_BITS} bits")

    def keyed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for rows in batches:
            fp, view = rows["fp"].to_numpy(np.int64), rows["view"].to_numpy(np.int64)
            for key in _keys(fp.view(np.uint64), budget):
                yield pd.DataFrame({"key": key | view << 40, "fp": fp, "node": rows["node"]})

    # made twice, which is cheaper than to write all keys: once to count, once to compare
    keys = views.mapInPandas(keyed, "key long, fp long, node long")
    hot = stage(keys.groupBy("key").count().where(F.col("count") > tile).select("key", F.ceil(F.col("count") / tile).cast("int").alias("tiles")), "simhash-hot")
    dealt = keys.join(hot, "key", "left")
    plain = dealt.where("tiles is null").select("key", "fp", "node")
    # a hot key has tiles; row tile t goes to the cells (t, u) and (u, t) for every tile u
    mine = F.pmod(F.xxhash64("fp", "node"), F.col("tiles")).cast("int")
    wide = dealt.where("tiles is not null").withColumn("mine", mine).select(
        "key", "fp", "node", "mine", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)).alias("u"),
    ).select("key", F.least("mine", "u").alias("low"), F.greatest("mine", "u").alias("high"), F.col("mine").alias("own"), "fp", "node")

    def in_order(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[pd.DataFrame] = []
        rows = 0
        for part in batches:
            held.append(part)
            rows += len(part)
            if rows < SLICE:
                continue
            whole = pd.concat(held)
            last = whole["key"].iloc[-1]
            done, rest = whole[whole["key"] != last], whole[whole["key"] == last]
            held, rows = [rest], len(rest)
            if len(done):
                yield out(done)
        if held and rows:
            yield out(pd.concat(held))

    def pairs(found: list[tuple[int, int]]) -> pd.DataFrame:
        return pd.DataFrame(np.array(found, np.int64).reshape(-1, 2), columns=["a", "b"])

    def out(rows: pd.DataFrame) -> pd.DataFrame:
        return pairs(_linked(rows["key"].to_numpy(np.int64), rows["fp"].to_numpy(np.int64).view(np.uint64), rows["node"].to_numpy(np.int64), budget))

    def one_cell(rows: pd.DataFrame) -> pd.DataFrame:
        fp, node, own = rows["fp"].to_numpy(np.int64).view(np.uint64), rows["node"].to_numpy(np.int64), rows["own"].to_numpy()
        low = rows["low"].iloc[0]
        left, right = (fp[own == low], node[own == low]), (fp[own != low], node[own != low])
        right = left if rows["high"].iloc[0] == low else right
        return pairs(_tile(left, right, int(_start(rows["key"].to_numpy(np.int64)[:1])[0]), budget, _Forest()))

    few = plain.repartition("key").sortWithinPartitions("key").mapInPandas(in_order, "a long, b long")
    many = wide.groupBy("key", "low", "high").applyInPandas(one_cell, "a long, b long")
    return few.unionByName(many)


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text: str = "text", budget: int = 3, shingle: int = 3, views: int = 1) -> DataFrame:
    """(id, fingerprint, component_id) for every row.

    Null and empty texts have fingerprint zero and link like any other; texts are read whole,
    however long. Ids keep their type; a component's id is the smallest in it, and a null id
    counts only if all are null. Repeated rows come back repeated, an empty table empty; other
    columns are ignored.
    """
    kind = docs.schema[id_col].dataType
    made = stage(fingerprints(docs, id_col, text, shingle, views).withColumn("id", F.col("id").cast(kind)), "simhash-fp")
    # cells, not single rows: a fingerprint that a third of the rows share is summed first
    first = stage(made.groupBy("fp").agg(F.min("id").alias("low"), F.count("*").alias("copies")), "simhash-distinct")
    own = F.concat(F.array("fp"), F.col("others"))
    seen = made.select("fp", "others").distinct().select(F.col("fp").alias("node"), F.posexplode(own).alias("view", "fp")).distinct()
    pairs = stage(links(stage(seen, "simhash-views"), budget), "simhash-links")
    member = min_label_components(pairs.select(F.col("a").alias("u"), F.col("b").alias("v"))).withColumnRenamed("v", "fp")
    known = stage(first.join(member, "fp", "left"), "simhash-known")
    linked = known.where("comp is not null")
    lowest = stage(linked.groupBy("comp").agg(F.min("low").alias("component_id"), F.count("*").alias("members")), "simhash-lowest")
    named = join_spread(linked, lowest, "comp", "members").select("fp", "copies", "component_id")
    named = stage(named.unionByName(known.where("comp is null").select("fp", "copies", F.col("low").alias("component_id"))), "simhash-named")
    hexed = F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint")
    return join_spread(made.select("id", "fp"), named, "fp", "copies").select(F.col("id").alias(id_col), hexed, "component_id")


def keep_first(docs: DataFrame, id_col: str = "doc_id", text: str = "text", budget: int = 3, shingle: int = 3, views: int = 1) -> DataFrame:
    """The rows of ``docs`` whose id is their component's smallest, with their columns.

    Rows without an id stay: nothing says which of them is first. Rows that repeat a kept id
    stay too.
    """
    kept = near_duplicates(docs, id_col, text, budget, shingle, views).where(F.col(id_col) == F.col("component_id")).select(F.col(id_col).alias("__kept")).distinct()
    return docs.join(kept, docs[id_col] == kept["__kept"], "left_semi").unionByName(docs.where(F.col(id_col).isNull()))
