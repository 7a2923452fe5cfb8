"""License scan by ordered signature rules, in DataFrame functions only.

A text is reduced to its lower-case words joined by single spaces. A keyword prefilter decides which texts meet the rules
at all, and each rule's own keyword decides whether its regular expression runs. The hits of a text, as intervals of
character positions, are resolved: a hit that lies within another one gives way to it when the other has a higher
priority, or the same priority and is longer or comes first in the rule order. The surviving hits give the labels and
the score.

Defined cases: null text counts as empty and has no words, hits or labels and score 0; repeated rows are scanned one by
one; an empty table gives an empty result; a text of any length is scanned whole.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: What separates words, once A-Z are lower-cased.
BREAK = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"

#: The base phrases and their labels.
BASE_PHRASES = {
    "gnu general public license": "gpl",
    "apache license": "apache",
    "cc by": "cc-by",
    "mit license": "mit",
}

#: Label, keyword, name pattern over spaced lower-case words. Every match of a pattern holds its keyword.
FAMILIES = [
    ("agpl", "affero", r"gnu affero general public licen[sc]e"),
    ("agpl", "agpl", r"agpl"),
    ("lgpl", "lesser", r"gnu lesser general public licen[sc]e"),
    ("lgpl", "library general", r"gnu library general public licen[sc]e"),
    ("lgpl", "lgpl", r"lgpl"),
    ("gpl", "general public", r"gnu general public licen[sc]e"),
    ("gpl", "gpl", r"(?:gnu )?gpl"),
    ("gfdl", "documentation", r"gnu free documentation licen[sc]e"),
    ("gfdl", "gfdl", r"gfdl"),
    ("apache", "apache", r"apache (?:software )?licen[sc]e"),
    ("mit", "mit", r"mit licen[sc]e"),
    ("mit", "expat", r"expat licen[sc]e"),
    ("bsd", "bsd", r"(?:new |modified |simplified |revised )?bsd (?:style )?licen[sc]e"),
    ("bsd", "clause bsd", r"(?:[0-4]|two|three|four) clause bsd(?: licen[sc]e)?"),
    ("bsd", "bsd", r"bsd [0-4] clause(?: [a-z]+)? licen[sc]e"),
    ("mpl", "mozilla", r"mozilla public licen[sc]e"),
    ("epl", "eclipse", r"eclipse public licen[sc]e"),
    ("eupl", "european union", r"european union public licen[sc]e"),
    ("cddl", "common development", r"common development and distribution licen[sc]e"),
    ("cpl", "common public", r"common public licen[sc]e"),
    ("isc", "isc", r"isc licen[sc]e"),
    ("zlib", "zlib", r"zlib(?: libpng)? licen[sc]e"),
    ("boost", "boost", r"boost software licen[sc]e"),
    ("artistic", "artistic", r"artistic licen[sc]e"),
    ("python", "python", r"python software foundation licen[sc]e"),
    ("postgresql", "postgresql", r"postgresql licen[sc]e"),
    ("unlicense", "unlicense", r"the unlicense"),
    ("wtfpl", "wtfpl", r"wtfpl"),
    ("ofl", "open font", r"(?:sil )?open font licen[sc]e"),
    ("odbl", "database", r"open (?:data commons )?(?:open )?database licen[sc]e"),
    ("openrail", "openrail", r"(?:creativeml )?openrail(?: m)?(?: licen[sc]e)?"),
    ("ms-pl", "microsoft public", r"microsoft public licen[sc]e"),
    ("ms-rl", "microsoft reciprocal", r"microsoft reciprocal licen[sc]e"),
    ("osl", "open software", r"open software licen[sc]e"),
    ("afl", "academic free", r"academic free licen[sc]e"),
    ("cecill", "cecill", r"cecill(?: [bc])?(?: licen[sc]e)?"),
    ("ecl", "educational community", r"educational community licen[sc]e"),
    ("upl", "universal permissive", r"universal permissive licen[sc]e"),
    ("sspl", "server side", r"server side public licen[sc]e"),
    ("bsl", "business source", r"business source licen[sc]e"),
    ("cc0", "cc0", r"cc0(?: public domain)?(?: dedication)?"),
    ("cc-by-nc-sa", "cc by nc sa", r"cc by nc sa"),
    ("cc-by-nc-nd", "cc by nc nd", r"cc by nc nd"),
    ("cc-by-nc", "cc by nc", r"cc by nc"),
    ("cc-by-sa", "cc by sa", r"cc by sa"),
    ("cc-by-nd", "cc by nd", r"cc by nd"),
    ("cc-by", "cc by", r"cc by"),
    ("cc-by-nc-sa", "creative commons", r"creative commons attribution non ?commercial share ?alike"),
    ("cc-by-nc-nd", "creative commons", r"creative commons attribution non ?commercial no ?derivatives"),
    ("cc-by-nc", "creative commons", r"creative commons attribution non ?commercial"),
    ("cc-by-sa", "creative commons", r"creative commons attribution share ?alike"),
    ("cc-by-nd", "creative commons", r"creative commons attribution no ?derivatives"),
    ("cc-by", "creative commons", r"creative commons attribution"),
    ("public-domain", "public domain", r"(?:in|into|to) the public domain"),
]

#: The wordings around a name: kind, prefix, suffix, priority, weight. The keyword stays the family's.
VERSION = r"(?: (?:version|v|ver) ?[0-9]{1,2}(?: [0-9]{1,2})?| v?[0-9](?: [0-9])?)?"
WORDINGS = [
    ("grant", r"(?:licensed|released|distributed|available|published|provided|covered|shared)(?: only)? under(?: the(?: terms(?: and conditions)? of the)?| a| an)? ", VERSION + r"(?: or (?:any )?later(?: version)?)?(?: licen[sc]e)?", 40, 1.0),
    ("terms", r"(?:under|by) the terms(?: and conditions)? of(?: either)?(?: the)? ", VERSION, 35, 0.95),
    ("tag", r"spdx licen[sc]e identifier ", VERSION + r"(?: only| or later)?", 45, 1.0),
    ("field", r"licen[sc]e (?:is |type |name )?(?:the )?", VERSION, 30, 0.9),
    ("version", r"(?:the )?", r" (?:version|v|ver) ?[0-9]{1,2}(?: [0-9]{1,2})?(?: or (?:any )?later(?: version)?)?", 20, 0.8),
    ("name", r"(?:the )?", r"", 10, 0.6),
]


@dataclass(frozen=True)
class Rule:
    """One signature; a higher priority wins over what it contains."""

    rule_id: str
    label: str
    keyword: str
    pattern: str
    priority: int
    weight: float


def signature_rules() -> list[Rule]:
    """Every family in every wording, in rule order."""
    return [
        Rule(f"{label}/{n}/{kind}", label, keyword, f"(?<= ){prefix}(?:{name}){suffix}(?= )", priority, weight)
        for n, (label, keyword, name) in enumerate(FAMILIES)
        for kind, prefix, suffix, priority, weight in WORDINGS
    ]


def normal_words(text: Column) -> Column:
    """The text's words with one space before, between and after; a single space if there are none."""
    lower = F.translate(F.coalesce(text, F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    inner = F.trim(F.regexp_replace(lower, BREAK, " "))
    return F.when(inner == "", F.lit(" ")).otherwise(F.concat(F.lit(" "), inner, F.lit(" ")))


def _rule_table(rules: list[Rule]) -> Column:
    return F.array(*[F.struct(F.lit(n).alias("n"), F.lit(r.label).alias("label"), F.lit(r.keyword).alias("keyword"), F.lit(r.pattern).alias("pattern"), F.lit(r.priority).alias("priority"), F.lit(r.weight).alias("weight")) for n, r in enumerate(rules)])


#: Intervals of all matches of the rules whose keyword the text has: [from, to) in characters.
_HITS = """flatten(transform(filter(lic_rules, r -> contains(lic_norm, r.keyword)), r ->
    zip_with(regexp_extract_all(lic_norm, r.pattern, 0), split(lic_norm, r.pattern, -1), (m, p) ->
        named_struct('n', r.n, 'label', r.label, 'priority', r.priority, 'weight', r.weight, 'hit', m, 'before', length(p), 'size', length(m)))))"""

#: Hits taken together, so that no expression walks all hits of a text for each of them.
BLOCK = 64

#: Pieces and matches of a rule add up to the text, so a running length modulo the text's is a place in it.
_SIZES = "transform(lic_raw, h -> cast(h.before + coalesce(h.size, 0) as bigint))"
_SUMS = f"transform(sequence(0, greatest(size(lic_raw) - 1, 0) div {BLOCK}), j -> aggregate(slice(lic_sizes, cast(j * {BLOCK} + 1 as int), {BLOCK}), 0L, (a, x) -> a + x))"
_STARTS = "transform(lic_sums, (s, j) -> aggregate(slice(lic_sums, 1, j), 0L, (a, x) -> a + x))"

#: zip_with pads the last piece, whose hit is null.
_PLACED = f"""filter(transform(lic_raw, (h, i) -> named_struct('n', h.n, 'label', h.label, 'priority', h.priority, 'weight', h.weight, 'hit', h.hit,
    'from', cast((get(lic_starts, cast(i div {BLOCK} as int)) + aggregate(slice(lic_sizes, cast((i div {BLOCK}) * {BLOCK} + 1 as int), i % {BLOCK}), 0L, (a, x) -> a + x)) % length(lic_norm) + h.before as int),
    'size', h.size)), h -> h.hit is not null)"""

#: Hits by place, in blocks with the places they span.
_SORTED = "transform(array_sort(transform(lic_hits, h -> named_struct('from', h.from, 'h', h))), x -> x.h)"
_BLOCKS = f"""transform(transform(sequence(0, greatest(size(lic_sorted) - 1, 0) div {BLOCK}), j -> slice(lic_sorted, cast(j * {BLOCK} + 1 as int), {BLOCK})), b -> named_struct('hits', b,
    'low', array_min(transform(b, h -> h.from)), 'high', array_max(transform(b, h -> h.from)), 'end', array_max(transform(b, h -> h.from + h.size))))"""

#: What may hold a hit of a block lies in the blocks that reach into it.
_NEAR = """transform(lic_blocks, s -> named_struct('hits', s.hits, 'near', flatten(transform(filter(lic_blocks, o -> o.low <= s.high and o.end > s.low), o -> o.hits))))"""

#: Containment: outranked by a hit around it.
_KEPT = """flatten(transform(lic_near, s -> filter(s.hits, a -> not exists(s.near, b -> (b.n <> a.n or b.from <> a.from) and b.from <= a.from and b.from + b.size >= a.from + a.size
    and (b.priority > a.priority or (b.priority = a.priority and (b.size > a.size or (b.size = a.size and b.n < a.n))))))))"""


def _keyword_gate(norm: Column, keywords: list[str]) -> Column:
    gate = F.lit(False)
    for k in keywords:
        gate = gate | F.contains(norm, F.lit(k))
    return gate


def scan(docs: DataFrame, rules: list[Rule] | None = None) -> DataFrame:
    """Add lic_norm, lic_hits (all hits) and lic_kept (those that no other hit suppresses) to a frame with `text`."""
    rules = signature_rules() if rules is None else rules
    keywords = sorted({r.keyword for r in rules})
    short = [k for k in keywords if not any(o != k and o in k for o in keywords)]
    none = "cast(array() as array<struct<n:int,label:string,priority:int,weight:double,hit:string,before:int,size:int>>)"
    staged = docs.withColumn("lic_norm", normal_words(F.col("text"))).withColumn("lic_gate", _keyword_gate(F.col("lic_norm"), short))
    staged = staged.withColumn("lic_rules", F.when(F.col("lic_gate"), _rule_table(rules)))
    staged = staged.withColumn("lic_raw", F.expr(f"case when lic_gate then {_HITS} else {none} end"))
    steps = {"lic_sizes": _SIZES, "lic_sums": _SUMS, "lic_starts": _STARTS, "lic_hits": _PLACED, "lic_sorted": _SORTED, "lic_blocks": _BLOCKS, "lic_near": _NEAR, "lic_kept": _KEPT}
    for name, step in steps.items():
        staged = staged.withColumn(name, F.expr(step))
    return staged.drop("lic_gate", "lic_rules", "lic_raw", *[name for name in steps if name not in ("lic_hits", "lic_kept")])


def base_matches(norm: Column) -> dict[str, Column]:
    """For the base phrases: count of places, first and last start word, labels."""
    count, first, last, labels = F.lit(0), [], [], []
    for phrase, label in BASE_PHRASES.items():
        spaced = f" {phrase} "
        has = F.contains(norm, F.lit(spaced))
        count = count + F.when(has, F.regexp_count(norm, F.lit(f"(?<= ){phrase}(?= )"))).otherwise(0)
        word = lambda at: (F.length(F.substr(norm, F.lit(1), at)) - F.length(F.replace(F.substr(norm, F.lit(1), at), F.lit(" "), F.lit(""))) - 1).cast("long")
        start = F.locate(spaced, norm)
        end = F.length(norm) - F.locate(spaced[::-1], F.reverse(norm)) - len(spaced) + 2
        first.append(F.when(has, word(start)))
        last.append(F.when(has, word(end)))
        labels.append(F.when(has, F.lit(label)))
    return {"n_base": count.cast("long"), "first_word": F.least(*first), "last_word": F.greatest(*last), "base": F.array_compact(F.array(*labels))}


def license_report(docs: DataFrame, rules: list[Rule] | None = None) -> DataFrame:
    """One row per document: base phrase counts, all labels, score, and the surviving hits as spans."""
    scanned = scan(docs.select("doc_id", "text"), rules)
    norm = F.col("lic_norm")
    base = base_matches(norm)
    scanned = scanned.select("doc_id", "lic_kept", norm, *[c.alias(k) for k, c in base.items()])
    return scanned.select(
        "doc_id",
        F.when(norm == " ", F.lit(0)).otherwise(F.length(norm) - F.length(F.replace(norm, F.lit(" "), F.lit(""))) - 1).cast("long").alias("n_words"),
        "n_base",
        "first_word",
        "last_word",
        F.array_join(F.array_sort(F.array_distinct("base")), ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_distinct(F.concat("base", F.transform("lic_kept", lambda h: h["label"])))), ",").alias("labels"),
        F.greatest(F.when(F.col("n_base") > 0, F.lit(0.6)).otherwise(F.lit(0.0)), F.coalesce(F.array_max(F.transform("lic_kept", lambda h: h["weight"])), F.lit(0.0))).alias("score"),
        F.transform("lic_kept", lambda h: F.struct(h["label"].alias("label"), h["from"].alias("start"), h["size"].alias("size"), h["hit"].alias("hit"))).alias("spans"),
    )
