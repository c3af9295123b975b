"""Secret scans over a trigram inverted index, in SQL functions alone.

Every rule is a regular expression. From it comes a Boolean query over trigrams that any
match must satisfy, as alternatives of conjunctions. The index holds, for each trigram that
the rules ask for, the list of rows whose text has it; it is written once to the shared
folder. The lists of each conjunction are intersected, those of the alternatives united; only
the rows that come out are scanned by the rule itself. A rule without mandatory trigrams
scans every text where it lies.

A row goes by a digest of its id and text. Two rows under one digest could only add a
candidate, never lose one, as every candidate is verified on its own text.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tourspark.llm.rows import fresh
from tourspark.llm.trigrams import query_of, trigrams_of
from tourspark.session import stage


@dataclass(frozen=True)
class Rule:
    """``least``: code points that ``group`` of a match must have, or the match is dropped."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 0
    ignore_case: bool = False

    @property
    def java(self) -> str:
        return ("(?i)" if self.ignore_case else "") + self.pattern

    @property
    def query(self):
        return query_of(self.pattern)


# The three base rules, then further public token formats.
BASE_RULES = (
    Rule("assign", r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 8, True),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 16),
    Rule("hex", r"[0-9a-f]+", 0, 32),
)
MORE_RULES = (
    Rule("pem", r"-----BEGIN [A-Z ]*PRIVATE KEY-----"),
    Rule("forge", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("chat", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("webtoken", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
)
RULES = BASE_RULES + MORE_RULES
#: Matches of a text in one block of the running sums.
BLOCK = 256


def vocabulary(rules=RULES) -> list[str]:
    """All trigrams that the rules ask for."""
    return sorted({t for r in rules for t in trigrams_of(r.query)})


def row_key(id_col: str, text: str) -> Column:
    return F.xxhash64(F.col(id_col), F.col(text))


def _text(value: str) -> str:
    """A string literal. Expressions here are SQL texts: they are large, and a call into the
    engine for each of their parts takes longer than small scans do."""
    return "'" + value.replace("\\", "\\\\").replace("'", "\\'") + "'"


def _name(column: str) -> str:
    return "`" + column.replace("`", "``") + "`"


def postings(docs: DataFrame, id_col: str = "doc_id", text: str = "text", rules=RULES) -> DataFrame:
    """The inverted index: one row (trigram, key) for each trigram of the rules in a text."""
    tests = ", ".join(f"CASE WHEN contains(folded, {_text(t)}) THEN {_text(t)} END" for t in vocabulary(rules))
    rows = docs.select(row_key(id_col, text).alias("key"), F.lower(F.col(text)).alias("folded"))
    return rows.select(F.expr(f"explode(array_compact(array({tests})))").alias("trigram"), "key")


def _branches(query) -> list[list[str]]:
    """Conjunctions of trigrams, one of which a match satisfies."""
    if isinstance(query, str):
        return [[query]]
    if query[0] == "or":
        return [b for p in query[1] for b in _branches(p)]
    out = [[]]
    for p in query[1]:
        out = [a + b for a in out for b in _branches(p)]
    return [sorted(set(b)) for b in out]


def candidates(index: DataFrame, rules=RULES) -> DataFrame:
    """(key, hits): the rows that satisfy a rule's query; bit r of ``hits`` is the rule's.

    The lists of a conjunction meet by row: partial unions of the trigrams seen come before
    the exchange, so a trigram that most texts have never meets in one task. Rules without
    trigrams have no candidates here.
    """
    asked = [
        f"struct({_text(t)} AS trigram, {r} AS rule, {n} AS branch, {1 << at}L AS bit, {(1 << len(b)) - 1}L AS whole)"
        for r, rule in enumerate(rules) if trigrams_of(rule.query) for n, b in enumerate(_branches(rule.query)) for at, t in enumerate(b)
    ]
    if not asked:
        return index.select("key", F.lit(0).cast("long").alias("hits")).where("false")
    # as many rows as the rules' queries have trigrams, a few dozen
    table = F.broadcast(index.sparkSession.range(1).select(F.expr(f"inline(array({', '.join(asked)}))")))
    met = index.join(table, "trigram").groupBy("key", "rule", "branch", "whole").agg(F.expr("bit_or(bit)").alias("seen")).where("seen = whole")
    return met.groupBy("key").agg(F.expr("bit_or(shiftleft(1L, rule))").alias("hits"))


def _with(value: str, name: str, use: str) -> str:
    """``use`` with ``name`` for the value, which is worked out once, however often it is used."""
    return f"element_at(transform(array({value}), {name} -> {use}), 1)"


def _places(body: str, rule: Rule) -> str:
    """array<struct<s, e>> of a rule's kept matches, leftmost and not overlapping.

    The text is split at the matches; the pieces between them and the matches themselves, in
    turn, give the places in code points as running sums. Those are taken within blocks and
    over the blocks' sums: an array that grows by one is copied at every step, so none here
    grows beyond a block or the number of blocks.
    """
    pattern = _text(rule.java)
    own = f"length(regexp_extract(m, {pattern}, {rule.group}))" if rule.group else "length(m)"
    steps = (
        f"filter(zip_with(transform(split({body}, {pattern}, -1), g -> length(g)), regexp_extract_all({body}, {pattern}, 0),"
        f" (gap, m) -> struct(gap AS gap, length(m) AS len, {own} AS own)), x -> x.len IS NOT NULL)"
    )
    count = f"cast(ceil(size(steps) / {BLOCK}) AS int)"
    blocks = f"transform(filter(sequence(0, {count}), k -> k < {count}), k -> slice(steps, k * {BLOCK} + 1, {BLOCK}))"
    bases = "aggregate(transform(blocks, b -> aggregate(b, 0, (acc, x) -> acc + x.gap + x.len)), array(0), (acc, x) -> concat(acc, array(element_at(acc, -1) + x)))"
    inside = (
        "aggregate(b, struct(element_at(bases, k + 1) AS at, cast(array() AS array<struct<s:int,e:int>>) AS out),"
        " (acc, x) -> struct(acc.at + x.gap + x.len AS at,"
        f" if(x.own >= {rule.least}, concat(acc.out, array(struct(acc.at + x.gap AS s, acc.at + x.gap + x.len AS e))), acc.out) AS out), acc -> acc.out)"
    )
    return _with(steps, "steps", _with(blocks, "blocks", _with(bases, "bases", f"flatten(transform(blocks, (b, k) -> {inside}))")))


def _gate(body: str, rule: Rule) -> str:
    """A cheap test before the places of a rule's matches are worked out."""
    pattern = rule.java
    if rule.group == 0 and rule.least and rule.pattern.endswith("]+") and rule.pattern.startswith("["):
        pattern = pattern.removesuffix("+") + f"{{{rule.least}}}"
    return f"rlike({body}, {_text(pattern)})"


def scan(docs: DataFrame, id_col: str = "doc_id", text: str = "text", rules=RULES, name: str = "found", index: DataFrame | None = None) -> DataFrame:
    """``docs`` with a column ``name``: array<struct<s, rank, kind, e>> in order.

    ``rank`` is the place of the kind among ``rules``. ``index``: the postings of these rows,
    if they have been written before. Null text counts as empty and has no spans; texts are
    read whole, however long; repeated rows come back repeated, an empty table empty; extra
    columns stay, but for one named like the new one.

    The candidates' table is written, so its size is known: the engine broadcasts it while it
    is small and else joins by the rows' digests.
    """
    index = stage(postings(docs, id_col, text, rules), "postings") if index is None else index
    key, hits = fresh("__key", docs.columns), fresh("__hits", docs.columns)
    chosen = stage(candidates(index, rules), "candidates").withColumnsRenamed({"key": key, "hits": hits})
    body = f"coalesce({_name(text)}, '')"

    def spans_of(rank: int, rule: Rule) -> str:
        spans = f"transform({_places(body, rule)}, p -> struct(p.s AS s, {rank} AS rank, {_text(rule.kind)} AS kind, p.e AS e))"
        asked = _gate(body, rule)
        if trigrams_of(rule.query):
            asked = f"(coalesce({_name(hits)}, 0L) & {1 << rank}L) > 0 AND {asked}"
        return f"CASE WHEN {asked} THEN {spans} ELSE cast(array() AS array<struct<s:int,rank:int,kind:string,e:int>>) END"

    found = f"array_sort(concat({', '.join(spans_of(rank, rule) for rank, rule in enumerate(rules))}))"
    rows = docs.withColumn(key, row_key(id_col, text)).join(chosen, key, "left")
    return rows.withColumn(name, F.expr(found)).drop(key, hits)


def joined(found: Column) -> Column:
    """kind:start:end of the spans, comma-joined."""
    return F.concat_ws(",", F.transform(found, lambda x: F.concat_ws(":", x["kind"], x["s"].cast("string"), x["e"].cast("string"))))


def redact(docs: DataFrame, id_col: str = "doc_id", text: str = "text", rules=RULES, mark: str = "[SECRET]") -> DataFrame:
    """``docs`` with every span replaced by ``mark``; overlapping spans become one mark. Null
    texts stay null, and every row stays, with its columns."""
    columns, found = docs.columns, fresh("__found", docs.columns)
    seen = scan(docs, id_col, text, rules, found)
    start = F.struct(F.lit("").alias("out"), F.lit(0).alias("at"))
    body = F.coalesce(F.col(text), F.lit(""))

    def step(acc, x):
        gap = F.substring(body, acc["at"] + 1, F.greatest(x["s"] - acc["at"], F.lit(0)))
        again = (x["s"] < acc["at"])
        return F.struct(F.concat(acc["out"], gap, F.when(again, F.lit("")).otherwise(F.lit(mark))).alias("out"), F.greatest(acc["at"], x["e"]).alias("at"))

    cleaned = F.aggregate(F.col(found), start, step, lambda acc: F.concat(acc["out"], F.substring(body, acc["at"] + 1, F.length(body))))
    return seen.withColumn(text, F.when(F.size(found) > 0, cleaned).otherwise(F.col(text))).select(*columns)


def digest(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """Counts, digest and spans of every document, under the three base kinds and the rest.

    Null and empty texts have no spans: counts of 0 and the digest of the empty text. Repeated
    rows come back repeated, an empty table empty; other columns are ignored.
    """
    found = scan(docs.select(F.col(id_col).alias(id_col), F.col(text).alias(text)), id_col, text).select(id_col, "found")
    count = lambda rank: F.size(F.filter("found", lambda x: x["rank"] == rank)).cast("long")
    base = F.filter("found", lambda x: x["rank"] < len(BASE_RULES))
    return found.select(
        id_col, count(0).alias("n_assign"), count(1).alias("n_access"), count(2).alias("n_hex"),
        F.sha2(joined(base), 256).alias("base_sha256"), joined(F.col("found")).alias("spans"),
    )


def oracle(rules=RULES) -> str:
    """The same digest in DuckDB, each rule scanned over every text."""
    parts = []
    for rank, r in enumerate(rules):
        pattern = r.java.replace("'", "''")
        own = f"length(regexp_extract(m, '{pattern}', {r.group}))" if r.group else "length(m)"
        parts.append(f"""
  SELECT doc_id, n, s, {rank} AS rank, '{r.kind}' AS kind, s + length(m) AS e FROM (
    SELECT doc_id, n, m, CAST(gap + coalesce(sum(gap + length(m)) OVER (PARTITION BY n ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS s
    FROM (SELECT doc_id, n, unnest(ms) AS m, generate_subscripts(ms, 1) AS i, length(gaps[generate_subscripts(ms, 1)]) AS gap
          FROM (SELECT doc_id, n, regexp_extract_all(body, '{pattern}') AS ms, string_split_regex(body, '{pattern}') AS gaps FROM d))
  ) WHERE {own} >= {r.least}""")
    return f"""
WITH d AS (SELECT doc_id, row_number() OVER () AS n, coalesce(text, '') AS body FROM documents),
spans AS ({' UNION ALL '.join(parts)}),
g AS (SELECT n, count(*) FILTER (WHERE rank = 0) AS a, count(*) FILTER (WHERE rank = 1) AS c, count(*) FILTER (WHERE rank = 2) AS h,
  coalesce(string_agg(kind || ':' || s || ':' || e, ',' ORDER BY s, rank) FILTER (WHERE rank < {len(BASE_RULES)}), '') AS base,
  string_agg(kind || ':' || s || ':' || e, ',' ORDER BY s, rank) AS spans FROM spans GROUP BY n)
SELECT doc_id, coalesce(a, 0) AS n_assign, coalesce(c, 0) AS n_access, coalesce(h, 0) AS n_hex,
  sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans FROM d LEFT JOIN g USING (n)
"""
