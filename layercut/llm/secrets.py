"""Operator 1 [native]: secret scans over a trigram inverted index.

From each rule's regular expression a Boolean query over trigrams is derived: which three-character strings every match must hold.
The index has a posting list of texts for each trigram that some query names, split into buckets of bounded size; lists are
intersected and united as the queries say, and only the texts found are verified with the expressions. Rules without mandatory
trigrams scan every text. Index keys are hashes of texts: texts that share a key share candidates, which verification sorts out.

Spans count code points, end exclusive; matches of a rule are leftmost and don't overlap; a match whose checked group is too short
is dropped after it was found, so it still hides what it covers.

Defined results: null and empty texts have no spans; repeated rows are scanned alike; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import product
from re import _parser as regex_parser

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut_lineage, spread, table


@dataclass(frozen=True)
class Rule:
    """Matches of pattern whose group holds least characters or more."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 0


def _either(words: str) -> str:
    return "|".join("".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in w) for w in words.split())


# The base rules of the contract. A run of hex digits below 32 can't start a longer one, so that the bound stands in the pattern.
BASE = [
    Rule("assign", "(" + _either("password passwd secret token api_key apikey") + ")[\"']?\\x20*[:=]\\x20*[\"']?([A-Za-z0-9+/_.=-]+)", 2, 8),
    Rule("access", "AKIA[A-Z0-9]+", 0, 16),
    Rule("hex", "[0-9a-f]{32,}", 0, 32),
]
# Public formats of further credentials.
MORE = [
    Rule("private_key", "-----BEGIN [A-Z ]*PRIVATE KEY-----"),
    Rule("code_host", "gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("chat_token", "xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("signed_token", "eyJ[A-Za-z0-9_-]{8,}\\.eyJ[A-Za-z0-9_-]{8,}\\.[A-Za-z0-9_-]{8,}"),
    Rule("url_login", "://[^\\x00-\\x20/:@\"'<>]+:[^\\x00-\\x20/:@\"'<>]+@"),
    Rule("cloud_key", "AIza[0-9A-Za-z_-]{35,}"),
]
RULES = BASE + MORE
#: Texts a bucket of the index holds about.
BUCKET_TEXTS = 512
#: Strings followed exactly while a query is derived.
MOST_STRINGS, MOST_CHARS = 64, 4

Query = list[frozenset[str]] | None  # a disjunction of conjunctions; None: no mandatory trigrams


def _both(a: Query, b: Query) -> Query:
    if a is None or b is None:
        return a if b is None else b
    return _least([x | y for x in a for y in b]) if len(a) * len(b) <= MOST_STRINGS else a


def _least(q: list[frozenset[str]]) -> list[frozenset[str]]:
    return [x for x in dict.fromkeys(q) if not any(y < x for y in q)]


def _strings(found: set[str]) -> Query:
    if min(map(len, found)) < 3:
        return None
    return _least([frozenset(s[i : i + 3] for i in range(len(s) - 2)) for s in sorted(found)])


def _derive(items) -> tuple[set[str] | None, Query]:
    """(all strings that items can match, if they are few; the query of a match)."""
    run, query, whole = {""}, None, True

    def flush() -> None:
        nonlocal run, query, whole
        query, run, whole = _both(query, _strings(run)), {""}, False

    def follow(options: set[str]) -> None:
        nonlocal run
        if len(run) * len(options) > MOST_STRINGS:
            flush()
        run = {a + b for a, b in product(run, options)}

    for op, arg in items:
        name = str(op)
        if name == "LITERAL":
            follow({chr(arg).lower()})
        elif name == "IN" and (chars := _few(arg)):
            follow(chars)
        elif name in ("SUBPATTERN", "BRANCH"):
            parts = [_derive(p) for p in ([arg[-1]] if name == "SUBPATTERN" else arg[1])]
            if all(p[0] is not None for p in parts) and len(every := set().union(*(p[0] for p in parts))) <= MOST_STRINGS:
                follow(every)
            else:
                flush()
                if all(p[1] is not None for p in parts):
                    query = _both(query, _least([x for p in parts for x in p[1]]))
        elif name in ("MAX_REPEAT", "MIN_REPEAT"):
            low, high, inner = arg
            exact, needs = _derive(inner)
            if exact is not None and high == 1:
                follow(exact | ({""} if low == 0 else set()))
            else:
                flush()
                if low > 0:
                    query = _both(query, needs)
        else:
            flush()
    return (run, _strings(run)) if whole else (None, _both(query, _strings(run)))


def _few(members) -> set[str] | None:
    out: set[str] = set()
    for op, arg in members:
        if str(op) == "LITERAL":
            out.add(chr(arg).lower())
        elif str(op) == "RANGE" and arg[1] - arg[0] < 2 * MOST_CHARS:
            out |= {chr(c).lower() for c in range(arg[0], arg[1] + 1)}
        else:
            return None
    return out if len(out) <= 2 * MOST_CHARS else None


def trigram_query(pattern: str) -> Query:
    """Lower-cased trigrams that a text with a match must hold, as a disjunction of conjunctions; None: scan everything."""
    return _derive(regex_parser.parse(pattern))[1]


def _codes_held(at: int, width: int) -> Column:
    return F.filter(F.array(*[F.lit(at + i) for i in range(width)]), lambda c: F.getbit(F.col(f"m{at}"), c - at) == 1)


def _with_bit(keys: Column, bit: int) -> Column:
    return F.transform(keys, lambda k: F.struct(k.alias("key"), F.lit(bit).alias("bit")))


def build_index(docs: DataFrame, trigrams: list[str], bucket_texts: int = BUCKET_TEXTS) -> DataFrame:
    """Postings (bucket, trigram, texts): sorted keys of the texts that hold a trigram."""
    buckets = spread(docs.count(), bucket_texts)
    low = docs.select(F.xxhash64("text").alias("k"), F.lower(F.coalesce(F.col("text"), F.lit(""))).alias("low"))
    masks = []
    for at in range(0, len(trigrams), 48):
        mask = F.lit(0).cast("long")
        for i, t in enumerate(trigrams[at : at + 48]):
            mask = mask + F.when(F.contains("low", F.lit(t)), 1 << i).otherwise(0)
        masks.append(mask.alias(f"m{at}"))
    held = low.select("k", *masks)
    codes = [_codes_held(at, len(trigrams[at : at + 48])) for at in range(0, len(trigrams), 48)]
    rows = held.select("k", F.pmod("k", F.lit(buckets)).alias("bucket"), F.explode(F.concat(*codes)).alias("trigram"))
    return rows.groupBy("bucket", "trigram").agg(F.sort_array(F.collect_set("k")).alias("texts"))


def candidates(index: DataFrame, queries: dict[int, Query], trigrams: list[str]) -> DataFrame:
    """(key, wanted): texts that satisfy queries; bit i of wanted: query i."""
    code = {t: i for i, t in enumerate(trigrams)}
    by = index.groupBy("bucket").agg(F.map_from_entries(F.collect_list(F.struct("trigram", "texts"))).alias("lists"))
    none = F.array().cast("array<bigint>")
    found = []
    for i, query in queries.items():
        every: Column = none
        for conjunction in query:
            held: Column | None = None
            for t in sorted(conjunction):
                of = F.coalesce(F.try_element_at("lists", F.lit(code[t])), none)
                held = of if held is None else F.array_intersect(held, of)
            every = F.array_union(every, held)
        found.append(_with_bit(every, 1 << i))
    return by.select(F.explode(F.concat(*found)).alias("x")).groupBy("x.key").agg(F.bit_or("x.bit").alias("wanted"))


def _starts(lengths: Column, first: Column, block: int = 256) -> Column:
    """Start of each match from lengths (gap before + match) and first (gaps): prefix sums in blocks, linear but for a factor of block."""
    total = lambda a: F.aggregate(a, F.lit(0), lambda s, x: s + x)
    sums = F.transform(F.sequence(F.lit(0), F.floor((F.size(lengths) - 1) / block).cast("int")), lambda b: total(F.slice(lengths, b * block + 1, block)))
    return F.transform(
        first, lambda gap, i: gap + total(F.slice(sums, 1, F.floor(i / block).cast("int"))) + total(F.slice(lengths, F.floor(i / block).cast("int") * block + 1, i % block))
    )


def _spans(df: DataFrame, at: int, rule: Rule, wanted: Column) -> DataFrame:
    """df with s<at>: structs (start, nth, kind, end) of the rule's matches."""
    none = F.array().cast("array<string>")
    text, pattern = F.col("scan_text"), F.lit(rule.pattern)
    df = df.withColumn("scan_hits", F.when(wanted, F.regexp_extract_all(text, pattern, F.lit(0))).otherwise(none))
    some = F.size("scan_hits") > 0
    df = df.withColumn("scan_gaps", F.when(some, F.slice(F.split(text, rule.pattern, -1), F.lit(1), F.size("scan_hits"))).otherwise(none))
    df = df.withColumn("scan_checked", F.when(some, F.regexp_extract_all(text, pattern, F.lit(rule.group))).otherwise(none)) if rule.group else df.withColumn("scan_checked", F.col("scan_hits"))
    df = df.withColumn("scan_gap_n", F.transform("scan_gaps", F.length)).withColumn("scan_hit_n", F.transform("scan_hits", F.length))
    df = df.withColumn("scan_both_n", F.zip_with("scan_gap_n", "scan_hit_n", lambda a, b: a + b))
    df = df.withColumn("scan_starts", F.when(some, _starts(F.col("scan_both_n"), F.col("scan_gap_n"))).otherwise(F.array().cast("array<int>")))
    made = F.transform(
        "scan_starts", lambda s, i: F.struct(s.alias("start"), F.lit(at).alias("nth"), F.lit(rule.kind).alias("kind"), (s + F.get("scan_hit_n", i)).alias("end"), F.length(F.get("scan_checked", i)).alias("size"))
    )
    return df.withColumn(f"scan_s{at}", F.filter(made, lambda x: x["size"] >= rule.least)).drop("scan_hits", "scan_gaps", "scan_checked", "scan_gap_n", "scan_hit_n", "scan_both_n", "scan_starts")


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")


def _scanned(docs: DataFrame, rules: list[Rule]) -> DataFrame:
    """scan_row (all columns of docs as one, so that no name clashes) and scan_spans."""
    queries = {i: trigram_query(r.pattern) for i, r in enumerate(rules)}
    trigrams = sorted({t for q in queries.values() if q for c in q for t in c})
    source = docs.select(F.col("text").cast("string").alias("text"))
    found = candidates(build_index(source, trigrams), {i: q for i, q in queries.items() if q}, trigrams)
    found = cut_lineage(found.select(F.col("key").alias("scan_found"), F.col("wanted").alias("scan_wanted")))
    text = F.col("text").cast("string")
    df = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("scan_row"), F.xxhash64(text).alias("scan_key"))
    df = df.join(found, F.col("scan_key") == F.col("scan_found"), "left").withColumn("scan_text", F.coalesce(F.col("scan_row")["text"].cast("string"), F.lit("")))
    for i, rule in enumerate(rules):
        df = _spans(df, i, rule, F.lit(True) if queries[i] is None else F.coalesce(F.col("scan_wanted").bitwiseAND(1 << i) != 0, F.lit(False)))
    return df.select("scan_row", F.sort_array(F.concat(*[F.col(f"scan_s{i}") for i in range(len(rules))])).alias("scan_spans"))


def scan(docs: DataFrame, rules: list[Rule] = RULES) -> DataFrame:
    """docs and secret_spans: structs (start, nth, kind, end, size) in the order of start, then rule. A column secret_spans of docs is replaced."""
    df = _scanned(docs, rules)
    return df.select(*[F.col("scan_row")[c].alias(c) for c in docs.columns if c != "secret_spans"], F.col("scan_spans").alias("secret_spans"))


def redact(docs: DataFrame, rules: list[Rule] = RULES, mark: str = "[secret]") -> DataFrame:
    """docs with every span's characters replaced by mark; touching and overlapping spans become one mark. Other columns stay."""
    df = _scanned(docs, rules).withColumn("scan_cuts", F.aggregate(
        "scan_spans", F.array().cast("array<struct<a:int,b:int>>"),
        lambda done, x: F.when(
            F.coalesce(F.element_at(F.concat(F.array(F.struct(F.lit(-1).alias("a"), F.lit(-1).alias("b"))), done), -1)["b"] >= x["start"], F.lit(False)),
            F.concat(F.slice(done, 1, F.size(done) - 1), F.array(F.struct(F.element_at(F.concat(F.array(F.struct(F.lit(-1).alias("a"), F.lit(-1).alias("b"))), done), -1)["a"].alias("a"), F.greatest(F.element_at(F.concat(F.array(F.struct(F.lit(-1).alias("a"), F.lit(-1).alias("b"))), done), -1)["b"], x["end"]).alias("b")))),
        ).otherwise(F.concat(done, F.array(F.struct(x["start"].alias("a"), x["end"].alias("b"))))),
    ))
    text = F.col("scan_row")["text"].cast("string")
    piece = F.transform("scan_cuts", lambda c, i: F.concat(F.substring(text, F.coalesce(F.get("scan_cuts", i - 1)["b"], F.lit(0)) + 1, c["a"] - F.coalesce(F.get("scan_cuts", i - 1)["b"], F.lit(0))), F.lit(mark)))
    last = F.element_at("scan_cuts", -1)["b"]
    clean = F.when(F.size("scan_cuts") > 0, F.concat(F.array_join(piece, ""), F.substring(text, last + 1, F.length(text)))).otherwise(F.col("scan_row")["text"])
    return df.select(*[(clean if c == "text" else F.col("scan_row")[c]).alias(c) for c in docs.columns])


def op1_secrets(spark, sf_dir: str) -> DataFrame:
    df = scan(table(spark, sf_dir, "documents").select("doc_id", "text")).drop("text")
    base = F.filter("secret_spans", lambda x: x["nth"] < len(BASE))
    count = lambda i: F.size(F.filter("secret_spans", lambda x: x["nth"] == i)).cast("long")
    return df.select("doc_id", count(0).alias("n_assign"), count(1).alias("n_access"), count(2).alias("n_hex"), F.sha2(_joined(base).cast("binary"), 256).alias("base_sha256"), _joined(F.col("secret_spans")).alias("spans"))


def _literal(pattern: str) -> str:
    return "'" + pattern.replace("'", "''") + "'"


def _oracle() -> str:
    """DuckDB: the rules on every text, without an index."""
    parts, lists = [], []
    for i, r in enumerate(RULES):
        p = _literal(r.pattern)
        parts.append(f"regexp_extract_all(t, {p}, 0) AS h{i}, regexp_extract_all(t, {p}, {r.group}) AS g{i}, string_split_regex(t, {p}) AS p{i}")
        before = f"coalesce(list_sum(list_transform(p{i}[1:k], lambda z: length(z))), 0) + coalesce(list_sum(list_transform(h{i}[1:k - 1], lambda z: length(z))), 0)"
        made = f"list_transform(range(1, len(h{i}) + 1), lambda k: {{'s': ({before})::BIGINT, 'n': {i}, 'kind': '{r.kind}', 'len': length(h{i}[k]), 'ok': length(g{i}[k]) >= {r.least}}})"
        lists.append(f"list_filter({made}, lambda x: x.ok)")
    show = lambda what: f"array_to_string(list_transform({what}, lambda x: x.kind || ':' || x.s || ':' || (x.s + x.len)), ',')"
    count = lambda i: f"len(list_filter(a, lambda x: x.n = {i}))::BIGINT"
    return f"""WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
m AS (SELECT doc_id, {', '.join(parts)} FROM d),
s AS (SELECT doc_id, list_sort(list_concat({', '.join(lists)})) AS a FROM m)
SELECT doc_id, {count(0)} AS n_assign, {count(1)} AS n_access, {count(2)} AS n_hex,
sha256(coalesce({show(f'list_filter(a, lambda x: x.n < {len(BASE)})')}, '')) AS base_sha256, coalesce({show('a')}, '') AS spans FROM s"""


ORACLE = _oracle()
