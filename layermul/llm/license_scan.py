"""License scan by ordered signature rules, natively: sentences of the licences' own texts, tags, and
mentions of their names.

Rules are regexes over the lower-cased text, each gated by one keyword: a text meets a rule's regex
only if it holds the rule's keyword. Detections carry their rule's priority; one that lies inside a
detection of higher priority, or of the same priority and longer (or equal and earlier in the rule
list), is suppressed.

Edge cases: a null text counts as empty: no words, no places, no labels, score 0; an empty table
gives an empty result; repeated rows each get their own result row; extra columns are ignored.
"""

from __future__ import annotations

import json
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .license_clauses import SENTENCES
from .scratch import table
from .spans import ascii_lower, quoted

# Fixed values of the contract: words after lower-casing, base phrases and their labels.
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
PHRASES = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
#: The same words before lower-casing, and what stands between them.
_RAW_WORD = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
_GAP = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"

# Label, the keyword that any mention holds, and how the licence is written in prose.
NAMES = (
    ("apache-2.0", "apache", r"apache(?: software)?(?: license)?,?(?: version| v\.?)? ?2(?:\.0)?"),
    ("apache-1.1", "apache", r"apache(?: software)?(?: license)?,?(?: version| v\.?)? ?1\.1"),
    ("mit", "mit", r"\bmit\b(?: license)?"),
    ("isc", "isc", r"\bisc\b(?: license)?"),
    ("bsd-2-clause", "bsd", r"(?:simplified bsd|bsd[- ]2[- ]clause|2[- ]clause bsd)(?: license)?"),
    ("bsd-3-clause", "bsd", r"(?:new bsd|modified bsd|bsd[- ]3[- ]clause|3[- ]clause bsd)(?: license)?"),
    ("bsd-4-clause", "bsd", r"(?:original bsd|bsd[- ]4[- ]clause|4[- ]clause bsd)(?: license)?"),
    ("gpl-1.0", "general public", r"(?:gnu )?general public license,?(?: version| v\.?) ?1(?:\.0)?"),
    ("gpl-2.0", "general public", r"(?:gnu )?general public license,?(?: version| v\.?) ?2(?:\.0)?"),
    ("gpl-3.0", "general public", r"(?:gnu )?general public license,?(?: version| v\.?) ?3(?:\.0)?"),
    ("lgpl-2.1", "general public", r"(?:gnu )?(?:lesser|library) general public license,?(?: version| v\.?) ?2\.[01]"),
    ("lgpl-3.0", "general public", r"(?:gnu )?lesser general public license,?(?: version| v\.?) ?3(?:\.0)?"),
    ("agpl-3.0", "affero", r"(?:gnu )?affero general public license,?(?: version| v\.?) ?3(?:\.0)?"),
    ("gfdl", "free documentation", r"(?:gnu )?free documentation license"),
    ("mpl-1.1", "mozilla", r"mozilla public license,?(?: version| v\.?) ?1\.1"),
    ("mpl-2.0", "mozilla", r"mozilla public license,?(?: version| v\.?) ?2(?:\.0)?"),
    ("epl-1.0", "eclipse", r"eclipse public license,?(?: version| v\.?|-) ?1\.0"),
    ("epl-2.0", "eclipse", r"eclipse public license,?(?: version| v\.?|-) ?2\.0"),
    ("cddl", "common development", r"common development and distribution license"),
    ("cpl-1.0", "common public", r"common public license"),
    ("artistic", "artistic", r"artistic license(?: ?(?:version )?[12]\.0)?"),
    ("bsl-1.0", "boost", r"boost software license"),
    ("zlib", "zlib", r"zlib(?:/libpng)? license"),
    ("unlicense", "unlicense", r"\bunlicense\b"),
    ("wtfpl", "wtfpl", r"\bwtfpl\b"),
    ("ofl-1.1", "open font", r"(?:sil )?open font license"),
    ("psf", "python software", r"python software foundation license"),
    ("postgresql", "postgresql", r"postgresql license"),
    ("openssl", "openssl", r"openssl license"),
    ("eupl", "european union", r"european union public licen[cs]e"),
    ("odbl", "open database", r"open database license"),
    ("cc0", "cc0", r"\bcc0\b(?: 1\.0)?"),
    ("cc-by", "cc", r"\bcc[- ]by\b(?![- ](?:sa|nc|nd)\b)(?:[- ][1-4]\.[05])?"),
    ("cc-by-sa", "cc", r"\bcc[- ]by[- ]sa\b(?:[- ][1-4]\.[05])?"),
    ("cc-by-nd", "cc", r"\bcc[- ]by[- ]nd\b(?:[- ][1-4]\.[05])?"),
    ("cc-by-nc", "cc", r"\bcc[- ]by[- ]nc\b(?![- ](?:sa|nd)\b)(?:[- ][1-4]\.[05])?"),
    ("cc-by-nc-sa", "cc", r"\bcc[- ]by[- ]nc[- ]sa\b(?:[- ][1-4]\.[05])?"),
    ("cc-by-nc-nd", "cc", r"\bcc[- ]by[- ]nc[- ]nd\b(?:[- ][1-4]\.[05])?"),
    ("cc-by", "creative commons", r"creative commons attribution(?![- ](?:share|non|no)) ?(?:[1-4]\.[05])?"),
    ("cc-by-sa", "creative commons", r"creative commons attribution[- ]share ?alike ?(?:[1-4]\.[05])?"),
    ("cc-by-nc", "creative commons", r"creative commons attribution[- ]non ?commercial(?![- ](?:share|no)) ?(?:[1-4]\.[05])?"),
)
# Identifiers as short tags name them.
TAGS = (
    "0bsd afl-3.0 agpl-1.0 agpl-3.0 apache-1.0 apache-1.1 apache-2.0 apsl-2.0 artistic-1.0 artistic-2.0 bsd-1-clause bsd-2-clause bsd-3-clause "
    "bsd-4-clause bsl-1.0 cc-by-1.0 cc-by-2.0 cc-by-2.5 cc-by-3.0 cc-by-4.0 cc-by-nc-3.0 cc-by-nc-4.0 cc-by-nc-nd-4.0 cc-by-nc-sa-4.0 cc-by-nd-4.0 "
    "cc-by-sa-3.0 cc-by-sa-4.0 cc0-1.0 cddl-1.0 cddl-1.1 cecill-2.1 cpl-1.0 ecl-2.0 epl-1.0 epl-2.0 eupl-1.1 eupl-1.2 gfdl-1.3 gpl-1.0 gpl-2.0 gpl-3.0 "
    "hpnd ipl-1.0 isc lgpl-2.0 lgpl-2.1 lgpl-3.0 lppl-1.3c mit mit-0 mpl-1.0 mpl-1.1 mpl-2.0 ms-pl ms-rl ncsa odbl-1.0 ofl-1.1 openssl osl-3.0 php-3.01 "
    "postgresql python-2.0 qpl-1.0 ruby sissl unlicense upl-1.0 vim w3c wtfpl x11 zlib zpl-2.1"
).split()
#: Names that are everyday words: alone they count only before "license".
_ALSO_WORDS = ("mit", "isc")

#: Templates over every name: how strong the wording is, and the regex around it.
_TEMPLATES = (
    (4, r"(?:licensed|released|distributed|published|available|redistributed) under (?:the )?(?:terms (?:and conditions )?of (?:the )?)?{}(?: license)?"),
    (3, r"(?:this|the) (?:work|software|program|file|code|text|document|library) (?:is|are) (?:licensed|released|covered|governed) (?:by|under) (?:the )?{}"),
    (2, r"\blicen[sc]e:? ?{}"),
    (1, r"{}"),
)


def rules() -> list[dict]:
    """All signature rules in order: id, label, priority 1 to 5, keyword, regex over lower-cased text."""
    out = [(label, 5, word, rx.replace(" ?", r"\s*").replace(" ", r"\s+")) for label, word, rx in SENTENCES]
    out += [(tag, 5, "spdx-license-identifier", r"spdx-license-identifier:\s*" + tag.replace(".", r"\.") + r"(?:-only|-or-later|\+)?(?![a-z0-9.-])") for tag in TAGS]
    for p, t in _TEMPLATES:
        for label, word, rx in NAMES:
            if label in _ALSO_WORDS:
                word, rx = (" under" if p > 2 else "licen"), (rx.replace("(?: license)?", " license") if p == 1 else rx)
            out.append((label, p, word, t.format(rx)))
    return [dict(id=i, label=label, prio=p, word=w, rx=rx) for i, (label, p, w, rx) in enumerate(out)]


def _detections(rule_list: list[dict]) -> tuple[Column, Column]:
    """The rules that match t, and their matches sorted by start, then the longest, the highest
    priority and the first rule."""
    words = sorted({r["word"] for r in rule_list})
    held = F.filter(F.array(*map(F.lit, words)), lambda w: F.expr("t").contains(w))
    by_word = json.dumps({w: [r for r in rule_list if r["word"] == w] for w in words})
    known = F.from_json(F.lit(by_word), "map<string,array<struct<id:int,label:string,prio:int,word:string,rx:string>>>")
    hits = F.filter(F.flatten(F.transform(held, lambda w: F.element_at(known, w))), lambda r: F.rlike(F.col("t"), r["rx"]))
    starts = """flatten(transform({hits}, r -> aggregate(
        zip_with(regexp_extract_all(t, r.rx, 0), slice(split(t, r.rx, -1), 1, size(regexp_extract_all(t, r.rx, 0))),
                 (m, s) -> named_struct('m', m, 's', s)),
        named_struct('at', 0L, 'out', cast(array() as array<struct<start:bigint,ends:bigint,prio:int,id:int,label:string>>)),
        (acc, x) -> named_struct('at', acc.at + length(x.s) + length(x.m), 'out', concat(acc.out, array(named_struct(
            'start', acc.at + length(x.s), 'ends', -(acc.at + length(x.s) + length(x.m)), 'prio', -r.prio, 'id', r.id, 'label', r.label)))),
        acc -> acc.out)))"""
    return hits, F.expr(f"array_sort({starts.format(hits='hits')})")


#: A container stands before what it contains in the sorted order, so the furthest end so far per
#: priority decides; ends, prio are negative in the sort structs.
_KEPT = """aggregate(found,
    named_struct('far', array_repeat(-1L, 6), 'out', cast(array() as array<struct<start:bigint,end:bigint,priority:int,label:string>>)),
    (acc, d) -> named_struct(
        'far', transform(acc.far, (e, p) -> if(p = -d.prio, greatest(e, -d.ends), e)),
        'out', if(array_max(slice(acc.far, 1 - d.prio, 6)) >= -d.ends, acc.out,
                  concat(acc.out, array(named_struct('start', d.start, 'end', -d.ends, 'priority', -d.prio, 'label', d.label))))),
    acc -> acc.out)"""


def scan_licenses(docs: DataFrame, rule_list: list[dict] | None = None) -> DataFrame:
    """One row per document: doc_id, n_words, base (array of phrase, n, first, last over the word
    sequence) and detections (array of start, end, priority, label in code points of the text)."""
    rule_list = rules() if rule_list is None else rule_list
    words = sorted({r["word"] for r in rule_list} - {"cc"}) + ["cc by", "cc-by"]
    lower = F.col("lower")  # for gates only: it may differ from the text's A-Z lower-casing in other letters
    gate = reduce(lambda a, b: a | b, [lower.contains(w) for w in words])
    phrase_gate = lower.contains("general") | lower.contains("reserved") | (lower.contains("cc") & lower.rlike(_GAP.join(["cc", "by"])))
    d = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("lower", F.lower("text"))
    d = d.select("doc_id", F.regexp_count("text", F.lit(_RAW_WORD)).cast("long").alias("n_words"),
                 F.when(phrase_gate, F.concat(F.lit(" "), F.array_join(F.regexp_extract_all(ascii_lower(F.col("text")), F.lit(WORD), F.lit(0)), " "), F.lit(" "))).alias("w"),
                 F.when(gate, ascii_lower(F.col("text"))).alias("t"))
    base = []
    for phrase in PHRASES:
        n = len(phrase.split())
        cut = f"split(w, {quoted(f'(?<= ){phrase}(?= )')}, -1)"
        count = "(length({0}) - length(replace({0}, ' ', '')))"
        base.append(F.when(F.col("w").contains(f" {phrase} "), F.expr(
            f"named_struct('phrase', '{phrase}', 'n', cast(size({cut}) - 1 as bigint), "
            f"'first', cast({count.format(f'{cut}[0]')} - 1 as bigint), "
            f"'last', n_words - ({count.format(f'element_at({cut}, -1)')} - 1) - {n})")))  # fmt: skip
    hits, found = _detections(rule_list)
    return (
        d.withColumn("base", F.array_compact(F.array(*base)))
        .withColumn("hits", F.when(F.col("t").isNotNull(), hits))
        .withColumn("found", F.when(F.size("hits") > 0, found))
        .withColumn("detections", F.when(F.col("found").isNotNull(), F.expr(_KEPT)))
        .select("doc_id", "n_words", "base", F.coalesce("detections", F.expr("cast(array() as array<struct<start:bigint,end:bigint,priority:int,label:string>>)")).alias("detections"))
    )


def op3_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The columns of op3_license_scan that hold the base phrases alone."""
    return op3_license_scan(spark, sf_dir).select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels")


def op3_base_oracle() -> str:
    """DuckDB SQL of op3_base."""
    n, upper = len(max(PHRASES, key=len).split()), "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    rows = ", ".join(f"({p.split() + [''] * (n - len(p.split()))!r}, {len(p.split())}, '{label}')" for p, label in PHRASES.items())
    return f"""WITH words AS (SELECT doc_id, row_number() OVER () AS rid, regexp_extract_all(translate(coalesce(text, ''), '{upper}', '{upper.lower()}'), '{WORD}') AS w FROM documents),
        phrases(parts, n, label) AS (VALUES {rows}),
        spots AS (SELECT rid, w, unnest(range(len(w))) AS spot FROM words),
        places AS (SELECT rid, label, spot FROM spots JOIN phrases ON w[spot + 1] = parts[1] AND w[spot + 1 : spot + n] = parts[1 : n])
        SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, count(spot) AS n_base, min(spot) AS first_word, max(spot) AS last_word, coalesce(string_agg(DISTINCT label, ',' ORDER BY label), '') AS base_labels
        FROM words LEFT JOIN places USING (rid) GROUP BY rid, doc_id, w"""


def op3_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan_licenses(table(spark, sf_dir, "documents").select("doc_id", "text"))
    label = F.create_map(*[F.lit(x) for kv in PHRASES.items() for x in kv])
    base = F.transform("base", lambda b: label[b["phrase"]])
    return found.select(
        "doc_id", "n_words",
        F.expr("aggregate(base, 0L, (a, b) -> a + b.n)").alias("n_base"),
        F.array_min(F.transform("base", lambda b: b["first"])).alias("first_word"),
        F.array_max(F.transform("base", lambda b: b["last"])).alias("last_word"),
        F.array_join(F.array_sort(base), ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_distinct(F.concat(base, F.transform("detections", lambda x: x["label"])))), ",").alias("labels"),
        F.greatest(F.coalesce(F.array_max(F.transform("detections", lambda x: x["priority"] / 5.0)), F.lit(0.0)), F.when(F.size("base") > 0, 0.5).otherwise(0.0)).alias("score"),
    )
