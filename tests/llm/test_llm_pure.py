"""Kernels of the pipeline operators against brute force, without Spark."""

import itertools
import random
import re

import numpy as np
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

import public_tokenizers
from tourspark.llm import blockjoin, bpe, langid, mtree, packing, quality, secrets, simhash, trigrams, wordpiece

WORDS = st.text(alphabet=st.sampled_from("ab é,.\n\tZß漢😀12'"), max_size=60)


# Trigram queries
@pytest.mark.parametrize(("pattern", "expected"), [
    ("AKIA[A-Z0-9]+", ("and", ("aki", "kia"))), ("[0-9a-f]+", trigrams.ANY), ("abc|abd", ("or", ("abc", "abd"))),
    ("ab?c", trigrams.ANY), ("(foo|ba)r", None), ("x{3}y", None),
])
def test_trigram_queries(pattern, expected):
    q = trigrams.query_of(pattern)
    if expected is not None:
        assert trigrams.holds(q, set()) == trigrams.holds(expected, set())
        assert set(trigrams.trigrams_of(q)) == set(trigrams.trigrams_of(expected))


@settings(max_examples=300, deadline=None)
@given(st.text(alphabet="abcdfor x", max_size=14))
def test_a_match_satisfies_its_query(text):
    have = {text.lower()[i : i + 3] for i in range(len(text) - 2)}
    for pattern in ("abc|a?bd+", "(foo|ba)r", "x{3}y?", "a[bc]d", "(a|b)(c|d)f", "for+x*d", "(abc)*dfo"):
        if re.search(pattern, text, re.I):
            assert trigrams.holds(trigrams.query_of(pattern), have)


def test_base_rules_have_the_queries_that_they_need():
    by = {r.kind: r.query for r in secrets.RULES}
    assert by["hex"] == trigrams.ANY
    for text in ("PassWord=1", "api_key: x", "APIKEY=x", "secret = y", "token:z", "passwd=q"):
        low = text.lower()
        assert trigrams.holds(by["assign"], {low[i : i + 3] for i in range(len(low) - 2)})


# BPE
@pytest.fixture(scope="module")
def reference():
    return tiktoken.Encoding("t", pat_str=public_tokenizers.PATTERN, mergeable_ranks=bpe.load(), special_tokens={})


def test_bpe_equals_tiktoken(reference):
    rng = random.Random(2)
    pool = [chr(c) for c in (*range(32, 127), *range(0xC0, 0x17F), *range(0x4E00, 0x4E40), 0x1F600, 10, 9, 13, 160)]
    texts = ["".join(rng.choice(pool) for _ in range(rng.randrange(120))) for _ in range(400)]
    texts += ["", " ", "a" * 5000, "ab" * 3000, " " * 3000 + "x", "\n \n" * 500, "<|endoftext|>"]
    coder = bpe.Coder()
    found = coder.encode(texts)
    assert found == [reference.encode_ordinary(t) for t in texts]
    assert [coder.decode(i) for i in found] == [t.encode() for t in texts]
    assert len(coder.encode(["hello world"])[0]) == len(reference.encode_ordinary("hello world"))


@settings(max_examples=100, deadline=None)
@given(WORDS)
def test_bpe_round_trip(text):
    coder = bpe.Coder()
    assert coder.decode(coder.encode([text])[0]) == text.encode()


def test_replay_takes_an_earlier_merge_that_appears_late():
    # "abc" has a lower rank than "ab": once "ab" is made at the left, it goes on at once
    ranks = {bytes([i]): 1000 + i for i in range(256)} | {b"abc": 1, b"ab": 2, b"ca": 3}
    pairs = {ranks[p[:i]] << 32 | ranks[p[i:]]: r for p, r in ranks.items() for i in range(1, len(p)) if p[:i] in ranks and p[i:] in ranks}

    def slow(word):
        parts = [bytes([c]) for c in word]
        while True:
            best = min(((ranks[parts[i] + parts[i + 1]], i) for i in range(len(parts) - 1) if parts[i] + parts[i + 1] in ranks), default=None)
            if best is None:
                return [ranks[p] for p in parts]
            i = best[1]
            parts[i : i + 2] = [parts[i] + parts[i + 1]]

    words = [bytes(c) for n in range(2, 8) for c in itertools.product(b"abc", repeat=n) if bytes(c) not in ranks]
    assert bpe.replay(words, ranks, pairs) == [slow(w) for w in words]


def test_each_distinct_word_is_replayed_once(monkeypatch):
    import pandas as pd

    words = sorted(["alpha", "beta", "beta", "beta", "delta", "delta", "gamma", "x" * 300_000])
    rows = pd.DataFrame({"run": range(len(words)), "n": 0, "word": words})
    seen: list[str] = []
    own = bpe.coder(bpe.RANKS)
    monkeypatch.setattr(own, "replay", lambda w: seen.extend(w) or bpe.Coder.replay(own, w))
    for cuts in ([0, 2, 3, 6, 8], [0, 8], list(range(9))):  # a word's rows may lie in several batches
        seen.clear()
        made = pd.concat(bpe._replayed(iter([rows.iloc[a:b] for a, b in zip(cuts, cuts[1:], strict=False)]), bpe.RANKS, 2))
        assert seen == sorted(set(words))
        assert [np.frombuffer(i, "<i4").tolist() for i in made["ids"]] == bpe.Coder().replay(words)


def test_letters_of_late_unicode_versions_are_cut_alike(reference):
    """Every code point between two letters, as the reference encoder has it."""
    texts = [f"a{chr(c)}b" for c in range(0x3400) if not 0xD800 <= c < 0xE000] + ["a₝b", "₝₝", " ₝1₝"]
    assert bpe.Coder().encode(texts) == [reference.encode_ordinary(t) for t in texts]


# Packing
def test_packing_ids_are_those_of_the_tokenizer_file():
    tok = Tokenizer.from_file(packing.VOCABULARY)
    rng = random.Random(9)
    texts = ["".join(chr(rng.choice([*range(32, 127), 10, 233, 0x4E2D])) for _ in range(80)) for _ in range(200)] + ["", "  a", "\n\n"]
    assert [packing.encoder().encode_ordinary(t) for t in texts] == [tok.encode(t, add_special_tokens=False).ids for t in texts]


def test_packing_ids_of_texts_with_added_tokens():
    tok, end = Tokenizer.from_file(packing.VOCABULARY), "<|endoftext|>"
    texts = [end, f"one {end} two", f"one  {end}  two\n\n{end}", end + end, f"x{end}y <|endoftext| >", "<|endof" + end + "text|>", "plain 'll  text"]
    assert [packing.ids_of(t) for t in texts] == [tok.encode(t, add_special_tokens=False).ids for t in texts]
    assert packing.ids_of(end) == [50256] != packing.encoder().encode_ordinary(end)


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(1, 90), max_size=40), st.integers(1, 32))
def test_balanced_pieces_cover_and_fill(lengths, length):
    pieces = list(packing.balanced(lengths, length))
    for d, n in enumerate(lengths):
        own = sorted((s, k) for e, s, k, _, _ in pieces if e == d)
        assert sum(k for _, k in own) == n and all(a + k == b for (a, k), (b, _) in zip(own, own[1:], strict=False))
    by = {}
    for _, _, k, s, o in pieces:
        by.setdefault(s, []).append((o, k))
    fills = []
    for rows in by.values():
        rows.sort()
        assert rows[0][0] == 0 and all(a + k == b for (a, k), (b, _) in zip(rows, rows[1:], strict=False))
        fills.append(sum(k for _, k in rows))
    # what isn't full is a power of two, each at most once, so nothing is padded
    short = [f for f in fills if f < length]
    assert all(f <= length for f in fills) and len(set(short)) == len(short) and all(f & f - 1 == 0 for f in short)


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(1, 90), max_size=40), st.integers(1, 32))
def test_balanced_takes_the_cheapest_sequence_with_room(lengths, length):
    """The rule by plain search over all sequences for every piece."""
    total = sum(lengths)
    room = [length] * (total // length)
    left = total % length
    while left:
        room.append(1 << left.bit_length() - 1)
        left -= room[-1]
    cost, want = [0.0] * len(room), []
    free = list(room)
    for d in sorted(range(len(lengths)), key=lambda d: (-(lengths[d] + lengths[d] ** 2 / 1024), d)):
        start = 0
        while start < lengths[d]:
            s = min((s for s in range(len(room)) if free[s]), key=lambda s: (cost[s], s))
            size = min(lengths[d] - start, free[s])
            want.append((d, start, size, s, room[s] - free[s]))
            free[s] -= size
            cost[s] += size + size * size / 1024
            start += size
    assert list(packing.balanced(lengths, length)) == want


def test_costs_are_closer_than_in_order_of_arrival():
    rng = random.Random(1)
    lengths = [rng.randint(1, 900) for _ in range(300)]
    cost, size = {}, {}
    for _, _, k, s, _ in packing.balanced(lengths):
        cost[s] = cost.get(s, 0) + k + k * k / 1024
        size[s] = size.get(s, 0) + k
    plain, at = [0.0], 0
    for n in lengths:
        while n:
            k = min(n, 1024 - at)
            plain[-1] += k + k * k / 1024
            at, n = at + k, n - k
            if at == 1024:
                plain.append(0.0)
                at = 0
    # full sequences against full sequences: the last in order of arrival is cut short
    assert np.std([c for s, c in cost.items() if size[s] == 1024]) < np.std(plain[:-1])


# Word pieces
def test_wordpiece_counts_equal_the_greedy_cut():
    vocabulary = {"a", "abc", "b", "bd", "abcde", "cd", "e", "x", "xy"}
    auto = wordpiece.Automaton(sorted(vocabulary))

    def greedy(w):
        i = n = 0
        while i < len(w):
            k = max((k for k in range(1, len(w) - i + 1) if w[i : i + k] in vocabulary), default=0)
            if not k:
                return -1
            i, n = i + k, n + 1
        return n

    for n in range(7):
        for c in itertools.product("abcde", repeat=n):
            assert auto.count("".join(c)) == greedy("".join(c))
    assert auto.count("a" * 20_000) == 20_000


def test_wordpiece_counts_on_the_real_vocabulary():
    """Greedy longest matches by plain search, over words of the documents and odd ones."""
    import duckdb
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=wordpiece.MODEL)
    ids = range(model.get_piece_size())
    pieces = {model.id_to_piece(i) for i in ids if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i))}
    longest, auto = max(map(len, pieces)), wordpiece.automaton()

    def greedy(w):
        i = n = 0
        while i < len(w):
            k = next((k for k in range(min(longest, len(w) - i), 0, -1) if w[i : i + k] in pieces), 0)
            if not k:
                return -1
            i, n = i + k, n + 1
        return n

    texts = [r[0] or "" for r in duckdb.sql("SELECT text FROM '/root/testdata/sf0.001/documents.parquet'").fetchall()]
    words = sorted({w for t in texts for w in t.split()}) + ["", "漢字", "😀", "x" * 5000, "naïve", "\u0301", "a▁b"]
    assert [auto.count("▁" + w) for w in words] == [greedy("▁" + w) for w in words]


# Language
def test_a_language_of_few_words_does_not_outbid_others():
    from collections import Counter

    en = "the quick brown foxes jump over a lazy dog while graphic stars perform in central squares of the morning sun"
    fr = "portez ce vieux whisky au juge blond qui fume pendant que la lune est en haut du mont et encore une fois"
    big = {"en": Counter({w: 500 for w in en.split()}), "fr": Counter({w: 500 for w in fr.split()})}
    small = big | {"xx": Counter({"zub": 1, "qwap": 1})}
    for text in ("Zygomorphic quasars perturb heliocentric spectrographs", "la lune inconnue encore", "the zubs"):
        assert langid.fit(small).predict(text, {})[0] == langid.fit(big).predict(text, {})[0]
    assert langid.fit(small).predict("zub qwap zub", {})[0] == "xx"
    # a language whose words are all single has a profile too
    assert langid.fit(small).table.shape[1] == 3 and "zub" in langid.fit(small).word


def test_language_against_plain_sums():
    """Scores by their definition: frequencies drawn down and floored, words before n-grams."""
    import math
    from collections import Counter

    words = {"aa": Counter({"thing": 5, "other": 5, "so": 1}), "bb": Counter({"ding": 7, "ander": 5})}
    model = langid.fit(words)

    def table(counts):
        total = {l: sum(c.values()) + langid.DRAWN for l, c in counts.items()}
        floor = 0.5 / max(total.values())
        return lambda g: [math.log(max(counts[l][g] / total[l], floor)) for l in sorted(counts)]

    grams = {n: {l: Counter() for l in words} for n in range(1, 5)}
    for l, c in words.items():
        for w, k in c.items():
            padded = f" {w} "
            for n in grams:
                for i in range(len(padded) - n + 1):
                    if padded[i : i + n] != " ":
                        grams[n][l][padded[i : i + n]] += k
    total = [0.0, 0.0]
    for w in ["thing", "dinger", "anso", "zzz", "other", "qq", "thing"]:
        if any(w in c for c in words.values()):
            own = table(words)(w)
        else:
            own, padded = [0.0, 0.0], f" {w} "
            for n in (4, 3, 2, 1):
                found = [g for i in range(len(padded) - n + 1) if any((g := padded[i : i + n]) in c for c in grams[n].values())]
                if found:
                    own = [sum(x) / len(found) for x in zip(*map(table(grams[n]), found), strict=True)]
                    break
        total = [a + b for a, b in zip(total, own, strict=True)]
    top = max(range(2), key=lambda i: total[i])
    lang, score, _ = model.judge("thing dinger anso zzz other qq thing", {})
    assert lang == ("aa", "bb")[top] and score == pytest.approx(1 / sum(math.exp(t - total[top]) for t in total))


def test_language_backs_off_to_shorter_grams():
    from collections import Counter

    model = langid.fit({"aa": Counter({"thing": 5, "other": 5}), "bb": Counter({"ding": 5, "ander": 5})})
    cache = {}
    assert model.predict("thing other", cache)[0] == "aa"
    assert model.predict("thinger", cache)[0] == "aa"  # unseen: its n-grams are known
    assert model.predict("anderding", cache)[0] == "bb"
    assert model.predict(None, cache) == model.predict("12 !", cache) == ("und", 0.0)
    assert 0 <= model.predict("zzz", cache)[1] <= 1


# Quality
def test_quality_separates_and_is_deterministic():
    rng = random.Random(4)
    good = ["the " + " ".join(rng.choice(["cat", "dog", "sat", "ran"]) for _ in range(20)) + "." for _ in range(60)]
    bad = [" ".join(rng.choice(["cat", "dog"]) + "###" for _ in range(20)) for _ in range(20)]
    model = quality.fit(good + bad, [1] * 60 + [0] * 20)
    again = quality.fit(good + bad, [1] * 60 + [0] * 20)
    assert model == again
    assert all(model.score(t, {}) >= 0.5 for t in good) and all(model.score(t, {}) < 0.5 for t in bad)
    assert 0 <= model.score(None, {}) == model.score("", {}) <= 1
    assert quality.fit([], []).score("x", {}) == 0.5
    assert quality.fit(["a"], [1]).score("x", {}) > 0.5


def test_the_fit_leans_on_the_grams_that_tell_classes_apart():
    texts, labels = ["aa bb", "aa cc", "dd bb", "dd cc"] * 3, [1, 1, 0, 0] * 3
    model = quality.fit(texts, labels, blend=0.0, rounds=500)
    words = model.weights[0]
    assert words["aa"] > 0 > words["dd"]
    assert abs(words.get("bb", 0.0)) < 1e-6 > abs(words.get("cc", 0.0)) - 1e-6
    assert model.score("aa bb", {}) > 0.5 > model.score("dd cc", {})


def test_quality_scores_against_plain_sums():
    """A score is the logistic curve over the bias and the weights of the text's n-grams."""
    import math

    texts, labels = ["The cat sat.", "the dog ran!", "BUY NOW!!! 99", "now now 12 BUY", "a cat, a dog"] * 4, [1, 1, 0, 0, 1] * 4
    model = quality.fit(texts, labels)
    for text in [*texts[:5], "an unseen cat!!!", "", None]:
        tokens = quality.TOKEN.findall(text or "")
        form = [quality.shape(t) for t in tokens]
        kinds = [set(tokens), set(itertools.pairwise(tokens)), {(f,) for f in form}, set(itertools.pairwise(form)), set(zip(form, form[1:], form[2:], strict=False))]
        margin = model.bias + sum(w.get(g, 0.0) for w, own in zip(model.weights, kinds, strict=True) for g in own)
        assert model.score(text, {}) == pytest.approx(1 / (1 + math.exp(-(model.slope * margin + model.shift))))


def test_the_hinge_fit_reaches_its_optimum():
    """Dual coordinate descent ends where no weight vector of a plain subgradient search does
    better on the primal objective."""
    rng = np.random.default_rng(3)
    words = [f"w{i}" for i in range(12)]
    texts = [" ".join(rng.choice(words[:8] if k % 2 else words[4:], 6)) for k in range(40)]
    y = np.array([k % 2 for k in range(40)])
    model = quality.fit(texts, y.tolist(), blend=0.0, rounds=3000)
    # the same features, scaled by their log-count ratios
    coded = [{(k, g) for k, kind in enumerate(quality.grams(t, {})) for g in kind} for t in texts]
    names = sorted({g for c in coded for g in c if sum(g in d for d in coded) >= 2}, key=str)
    x = np.array([[g in c for g in names] for c in coded], float)
    p, q = 1 + x[y == 1].sum(0), 1 + x[y == 0].sum(0)
    ratio = np.log(p / (20 + 2)) - np.log(q / (20 + 2))
    scaled, sign = x * ratio, np.where(y == 1, 1.0, -1.0)
    value = lambda w, b: 0.5 * (w @ w + b * b) + 0.1 * np.maximum(0, 1 - sign * (scaled @ w + b)).sum()
    weight = np.array([model.weights[k].get(g, 0.0) for k, g in names])
    own = np.divide(weight, ratio, out=np.zeros(len(names)), where=ratio != 0)
    w, b, best = np.zeros(len(names)), 0.0, np.inf
    for step in range(1, 4000):
        short = sign * (scaled @ w + b) < 1
        w, b = w - 0.05 / step**0.5 * (w - 0.1 * (sign * short) @ scaled), b - 0.05 / step**0.5 * (b - 0.1 * (sign * short).sum())
        best = min(best, value(w, b))
    assert value(own, model.bias) <= best + 1e-3


# SimHash
def slow_fingerprint(text, k=3):
    import xxhash

    words = [w for w in re.split(r"[\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")) if w]
    grams = [" ".join(words[i : i + k]) for i in range(len(words) - k + 1)] if len(words) >= k else [" ".join(words)] if words else []
    hashes = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


@settings(max_examples=200, deadline=None)
@given(WORDS)
def test_fingerprints(text):
    assert simhash.fingerprint(text) == slow_fingerprint(text)


@pytest.mark.parametrize("budget", [0, 1, 2, 3, 5, 7])
def test_pigeonring_loses_no_pair(budget):
    rng = np.random.default_rng(3)
    base = rng.integers(0, 2**63, 150, dtype=np.uint64)
    pool = [base]
    for flips in range(1, budget + 2):
        x = base.copy()
        for _ in range(flips):
            x ^= np.uint64(1) << rng.integers(0, 64, len(x)).astype(np.uint64)
        pool.append(x)
    fp = np.unique(np.concatenate(pool))
    node = np.arange(len(fp))
    made = simhash._keys(fp, budget)
    keys, order = np.concatenate(made), np.argsort(np.concatenate(made), kind="stable")
    found = simhash._linked(keys[order], np.tile(fp, len(made))[order], np.tile(node, len(made))[order], budget)
    near = np.bitwise_count(fp[:, None] ^ fp[None, :]) <= budget

    def groups(pairs):
        up = simhash._Forest()
        for a, b in pairs:
            up.join(a, b)
        return [up.root(int(x)) for x in node]

    i, j = np.nonzero(near)
    assert groups(found) == groups(zip(i.tolist(), j.tolist(), strict=True))
    assert all(near[a, b] for a, b in found)


@pytest.mark.parametrize("budget", [1, 3, 5])
def test_chains_drop_pairs_before_the_full_distance(budget):
    """Counted by hand: a pair is dropped at the first chain that breaks its budget."""
    rng = np.random.default_rng(7)
    x, start = rng.integers(0, 2**63, 4000, dtype=np.uint64), rng.integers(0, budget + 1, 4000)
    for _ in range(3):
        x[:3000] &= rng.integers(0, 2**63, 3000, dtype=np.uint64)
    dropped, m = np.zeros(budget + 1, np.int64), budget + 1
    kept = simhash.chain_survivors(x, start, budget, dropped)
    want, survivors = [0] * m, []
    for k, (v, s) in enumerate(zip(x.tolist(), start.tolist(), strict=True)):
        total = 0
        for step in range(m):
            shift, width = simhash.segments(budget)[(s + step) % m]
            total += (v >> shift & (1 << width) - 1).bit_count()
            if total * m > (step + 1) * budget:
                want[step] += 1
                break
        else:
            survivors.append(k)
            assert v.bit_count() <= budget
    assert kept.tolist() == survivors and dropped.tolist() == want
    assert dropped[:-1].sum() > 0.9 * dropped.sum() > 0


def test_most_pairs_under_a_key_never_come_to_the_full_distance():
    rng = np.random.default_rng(4)
    base = np.uint64(0x5A5A0F0F12345678)
    fp = np.unique(base ^ (rng.integers(0, 2**63, 300, dtype=np.uint64) & ~np.uint64(0xFFFFFF)))  # one key of segment 0
    dropped = np.zeros(4, np.int64)
    order = np.argsort(simhash._keys(fp, 3)[0], kind="stable")
    simhash._linked(simhash._keys(fp, 3)[0][order], fp[order], np.arange(len(fp)), 3, dropped)
    assert dropped[-1] < 0.05 * dropped.sum()


# Vector searches
def test_mtree_finds_the_nearest():
    rng = np.random.default_rng(5)
    raw = np.floor(256 * rng.normal(0, 0.13, (3000, 16)))
    raw[100:400] = raw[100]
    top = (raw**2).sum(axis=1).max()
    tree = mtree.MTree(np.arange(len(raw)), mtree.lift(raw, top), 64)
    for r in range(0, 3000, 97):
        found = sorted(i for _, i in tree.search(np.append(raw[r], 0.0), 5))
        score = raw @ raw[r]
        best = np.lexsort((np.arange(len(raw)), -score))[:5]
        assert set(best) <= set(found)


def test_tile_bounds_hold_and_heaps_are_exact():
    rng = np.random.default_rng(6)
    x, y = rng.normal(size=(40, 24)) * rng.lognormal(size=(40, 1)), rng.normal(size=(500, 24))
    y[10:60] = y[10]
    near, error = blockjoin.tile_bounds(blockjoin.Cut(x), blockjoin.Cut(y))
    assert (np.abs(near - x @ y.T) <= error).all()
    heaps = blockjoin.Heaps(np.arange(40), x, 20)
    for at in range(0, 500, 77):
        heaps.offer(np.arange(at, min(500, at + 77)) + 1000, y[at : at + 77])
    rows = heaps.rows(np.arange(40))
    for i in range(40):
        score = blockjoin.dots(np.repeat(x[i : i + 1], 500, 0), y)
        best = np.lexsort((np.arange(500), -score))[:20]
        own = rows[rows["query_id"] == i].sort_values(["score", "vec_id"], ascending=[False, True])
        assert own["vec_id"].tolist() == (best + 1000).tolist()
