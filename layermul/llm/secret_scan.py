"""Secret scan with a trigram inverted index.

Each rule's regex is compiled to a Boolean trigram query (an OR of trigram sets that every match
must hold). Postings of just the trigrams that some query names are built over all documents, in
blocks of bounded size, intersected per rule, and the candidates verified by the regex itself.
Rules without mandatory trigrams scan every text.

Edge cases: a null text counts as empty and has no spans; an empty table gives an empty result;
repeated rows each get their own result row; extra columns are ignored.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from itertools import product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .scratch import broadcast_if_small, materialize, table
from .spans import SPAN, match_spans, span_sql, span_text

_parser = re._parser


@dataclass(frozen=True)
class SecretRule:
    """kind: name in the spans; least: shortest accepted length of `group`, tested after matching."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 0
    base: bool = False


# The contract's three base rules, then published shapes of provider keys.
RULES = (
    SecretRule("assign", r"(?i)(password|passwd|secret|token|api_?key)[\x22\x27]?\x20*[:=]\x20*[\x22\x27]?([A-Za-z0-9+/_.=-]+)", 2, 12, True),
    SecretRule("access", r"AKIA[A-Z0-9]+", 0, 18, True),
    SecretRule("hex", r"[0-9a-f]+", 0, 16, True),
    SecretRule("aws_temporary", r"ASIA[A-Z0-9]{16}"),
    SecretRule("github", r"gh[opsur]_[A-Za-z0-9]{36}"),
    SecretRule("github_fine", r"github_pat_[A-Za-z0-9_]{40,}"),
    SecretRule("gitlab", r"glpat-[A-Za-z0-9_-]{20}"),
    SecretRule("google", r"AIza[A-Za-z0-9_-]{35}"),
    SecretRule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
    SecretRule("npm", r"npm_[A-Za-z0-9]{36}"),
    SecretRule("private_key", r"-----BEGIN (?:RSA |EC |DSA |OPENSSH |PGP |ENCRYPTED )?PRIVATE KEY(?: BLOCK)?-----"),
    SecretRule("pypi", r"pypi-AgEI[A-Za-z0-9_-]{20,}"),
    SecretRule("sendgrid", r"SG\.[A-Za-z0-9_-]{20,}\.[A-Za-z0-9_-]{20,}"),
    SecretRule("slack", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    SecretRule("slack_hook", r"hooks\.slack\.com/services/[A-Za-z0-9/]{20,}"),
    SecretRule("stripe", r"[rs]k_(?:live|test)_[A-Za-z0-9]{16,}"),
    SecretRule("url_login", r"[a-z][a-z0-9+.-]*://[^/\s:@]{1,64}:[^/\s:@]{3,64}@"),
)

_BRANCHES, _SMALL_CLASS, _UNROLL = 64, 6, 8


def trigram_query(pattern: str) -> list[frozenset[str]] | None:
    """The regex as an OR of sets of lower-cased trigrams, each set wholly present in any match of
    its branch; None where some branch has no mandatory trigram."""

    def extend(paths: list[tuple[str, ...]], tails: list[tuple[str, ...]]) -> list[tuple[str, ...]]:
        out = list({p[:-1] + (p[-1] + t[0],) + t[1:] for p, t in product(paths, tails)})
        return out if len(out) <= _BRANCHES else cut(paths)

    def cut(paths: list[tuple[str, ...]]) -> list[tuple[str, ...]]:
        return list({p + ("",) if p[-1] else p for p in paths})

    def walk(seq) -> list[tuple[str, ...]]:
        paths: list[tuple[str, ...]] = [("",)]
        for op, arg in seq:
            name = str(op)
            if name == "LITERAL":
                paths = extend(paths, [(chr(arg).lower(),)])
            elif name == "IN" and all(str(k) == "LITERAL" for k, _ in arg) and len(arg) <= _SMALL_CLASS:
                paths = extend(paths, [(chr(v).lower(),) for _, v in arg])
            elif name == "SUBPATTERN":
                paths = extend(paths, walk(arg[3]))
            elif name == "BRANCH":
                paths = extend(paths, [p for one in arg[1] for p in walk(one)])
            elif name in ("MAX_REPEAT", "MIN_REPEAT"):
                low, high, item = arg
                inner = walk(item)
                if (low, high) == (0, 1):
                    paths = extend(paths, [("",), *inner])
                else:
                    for _ in range(min(low, _UNROLL)):
                        paths = extend(paths, inner)
                    paths = cut(paths) if high != low or low > _UNROLL else paths
            elif name != "AT":
                paths = cut(paths)
        return paths

    sets = {frozenset(run[i : i + 3] for run in path for i in range(len(run) - 2)) for path in walk(_parser.parse(pattern))}
    if not all(sets):
        return None
    return sorted((s for s in sets if not any(t < s for t in sets)), key=sorted)


def _trie_pattern(words: list[str]) -> str:
    """All words as one regex with shared first letters."""
    firsts: dict[str, list[str]] = {}
    for w in sorted(words):
        firsts.setdefault(w[0], []).append(w[1:])
    parts = [re.escape(c) + ("(?:" + "|".join(map(re.escape, rest)) + ")") for c, rest in firsts.items()]
    return "|".join(parts)


def build_postings(docs: DataFrame, trigrams: list[str], rows_per_block: int = 4096) -> DataFrame:
    """(block, trigram, postings): the sorted keys of the documents of one block that hold the
    trigram. A block has about rows_per_block documents, so no list grows with the corpus.
    docs has columns key and text."""
    blocks = max(1, -(-docs.count() // rows_per_block))
    held = F.array_distinct(F.expr(f"regexp_extract_all(lower(text), r'(?=({_trie_pattern(trigrams)}))', 1)"))
    return (
        docs.select("key", F.explode(held).alias("trigram"))
        .withColumn("block", F.pmod(F.col("key"), F.lit(blocks)))
        .groupBy("block", "trigram")
        .agg(F.sort_array(F.collect_set("key")).alias("postings"))
    )


def index_candidates(postings: DataFrame, queries: dict[int, list[frozenset[str]]]) -> DataFrame:
    """(key, rules): for each document the rules whose Boolean query it meets, by intersecting the
    postings of each alternative within each block. queries has a bounded number of static rows."""
    spark = postings.sparkSession
    wanted = [(rule, alt, t, len(s)) for rule, alts in queries.items() for alt, s in enumerate(alts) for t in sorted(s)]
    q = F.broadcast(spark.createDataFrame(wanted, "rule int, alt int, trigram string, needed int"))
    met = (
        postings.join(q, "trigram")
        .groupBy("block", "rule", "alt", "needed")
        .agg(F.collect_list("postings").alias("lists"))
        .where(F.size("lists") == F.col("needed"))
        .select("rule", F.explode(F.expr("aggregate(slice(lists, 2, size(lists)), lists[0], (a, b) -> array_intersect(a, b))")).alias("key"))
    )
    return met.groupBy("key").agg(F.collect_set("rule").alias("rules"))


def scan_secrets(docs: DataFrame, rules: tuple[SecretRule, ...] = RULES) -> DataFrame:
    """One row per document: doc_id and spans, array<struct<start, rank, end, kind>> sorted by start,
    then by the rules' order."""
    keyed = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("key", F.xxhash64("doc_id", "text"))
    queries = {i: q for i, r in enumerate(rules) if (q := trigram_query(r.pattern))}
    found = keyed
    if queries:
        vocabulary = sorted({t for alts in queries.values() for s in alts for t in s})
        hits = materialize(index_candidates(build_postings(keyed.select("key", "text"), vocabulary), queries), "secret-candidates")
        found = keyed.join(broadcast_if_small(hits, hits.count()), "key", "left")
    parts = []
    for i, r in enumerate(rules):
        # a run of 16+ characters of one class is a maximal run that passes, so the scan can ask for it at once
        fast = r.pattern[:-1] + "{%d,}" % r.least if i not in queries and re.fullmatch(r"\[[^\]]+\]\+", r.pattern) else r.pattern
        spans = match_spans("text", fast, r.kind, i, r.group, r.least)
        parts.append(spans if i not in queries else F.when(F.array_contains("rules", i), spans).otherwise(F.lit(None).cast(SPAN)))
    some = [F.coalesce(p, F.expr(f"cast(array() as {SPAN})")) for p in parts]
    return found.select("doc_id", F.array_sort(F.concat(*some)).alias("spans"))


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan_secrets(table(spark, sf_dir, "documents").select("doc_id", "text"))
    base = [r.kind for r in RULES if r.base]
    counts = [F.expr(f"cast(size(filter(spans, x -> x.rank = {i})) as bigint)").alias(f"n_{k}") for i, k in enumerate(base)]
    own = F.filter("spans", lambda x: x["rank"] < len(base))
    return found.select("doc_id", *counts, F.sha2(span_text(own), 256).alias("base_sha256"), span_text(F.col("spans")).alias("spans"))


def op7_oracle() -> str:
    joined = "array_to_string(list_transform({}, lambda x: x.kind || ':' || x.start || ':' || x.end), ',')"
    counts = ", ".join(f"len(list_filter(s, lambda x: x.rank = {i}))::BIGINT AS n_{r.kind}" for i, r in enumerate(RULES) if r.base)
    return f"""WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
      {span_sql([(r.pattern, r.kind, r.group, r.least) for r in RULES], "d")}
      SELECT doc_id, {counts}, sha256({joined.format("list_filter(s, lambda x: x.rank < 3)")}) AS base_sha256,
             {joined.format("s")} AS spans FROM spanned"""
