"""Personal data: fixed formats, and contexts bootstrapped from them.

Only DataFrame functions run here.  Positions come from splitting a text by the
same pattern that extracts the matches: the gaps' lengths place the matches.
The patterns are written with possessive repeats and anchored at run starts
(``\\G`` or a look-behind), so they find what the plain forms find but take time
linear in the text, however long its runs are.

Bootstrapping: identifier-like tokens that hold a base match are seeds.  The one,
two and three words before a token and after it are its lexical patterns.  On
the graph of (pattern, instance) a pattern's score for a kind is the smoothed
share of score that its instances carry (instances without a score whose form
suits the kind say little against it and count ``doubt``, others count fully);
patterns with ``support`` different seeds and a score of ``confidence`` are
believed.  Unseen instances of a
believed pattern whose own form suits the kind take the pattern's score and are
seeds of the next round, so that contexts found through them are learnt as well,
until nothing new is found or ``rounds`` have run.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .workspace import Workspace

KINDS = ("email", "ip", "card", "phone")
#: Linear-time forms of the base patterns.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++(?:\.[0-9]++)(?:\.[0-9]++)(?:\.[0-9]++)",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: An identifier-like token: a run of non-blanks with a digit or @, and runs with digits right after it.
TOKEN = r"(?<!\S)[^\s0-9@]*+[0-9@]\S*+(?:\x20[^\s0-9@]*+[0-9]\S*+)*+"
_BLOCK = 256


@dataclass(frozen=True)
class BootstrapSettings:
    """rounds of scoring; confidence and support that a pattern needs; doubt and smoothing of its
    share; words: length of the longest pattern."""

    rounds: int = 4
    confidence: float = 0.75
    support: int = 8
    doubt: float = 0.1
    smoothing: float = 1.0
    words: int = 3


def _running(values: Column) -> Column:
    """Exclusive running sums of an array of longs."""
    start = F.struct(F.array().cast("array<bigint>").alias("sums"), F.lit(0).cast("bigint").alias("at"))
    step = lambda acc, x: F.struct(F.concat(acc["sums"], F.array(acc["at"])).alias("sums"), (acc["at"] + x).alias("at"))
    return F.aggregate(values, start, step, lambda acc: acc["sums"])


def _placed(frame: DataFrame, name: str, pattern: str, maybe: Column, words: int = 0) -> DataFrame:
    """Adds column ``name``: the matches in order as structs (start, end, value), code points.

    With ``words``, also the last words before (left) and first words after (right)
    each match, as far as the neighbouring matches, lower-cased and one space apart.

    Running sums are taken in blocks of 256 and over blocks, so texts with very
    many matches do not copy long arrays again and again.
    """
    pat = F.lit(pattern)
    none = F.array().cast("array<string>")
    frame = frame.withColumn(f"{name}_m", F.when(maybe, F.regexp_extract_all("text", pat, F.lit(0))).otherwise(none))
    frame = frame.withColumn(f"{name}_g", F.when(F.size(f"{name}_m") > 0, F.split("text", pattern, -1)).otherwise(none))
    found, gaps = F.col(f"{name}_m"), F.col(f"{name}_g")
    size = F.size(found)
    steps = F.transform(found, lambda m, i: (F.char_length(m) + F.char_length(F.element_at(gaps, i + 1))).cast("bigint"))
    frame = frame.withColumn(f"{name}_s", steps)
    ends = F.sequence(F.lit(1), F.greatest(size, F.lit(1)), F.lit(_BLOCK))
    blocks = F.transform(ends, lambda b: F.slice(F.col(f"{name}_s"), b, _BLOCK))
    frame = frame.withColumn(f"{name}_b", F.when(size > 0, blocks).otherwise(F.array().cast("array<array<bigint>>")))
    sums = F.transform(F.col(f"{name}_b"), lambda b: F.aggregate(b, F.lit(0).cast("bigint"), lambda s, x: s + x))
    inner = F.flatten(F.transform(F.col(f"{name}_b"), _running))
    frame = frame.withColumn(f"{name}_o", _running(sums)).withColumn(f"{name}_i", inner)

    def place(m: Column, i: Column) -> Column:
        gap = F.element_at(gaps, i + 1)
        start = F.element_at(f"{name}_o", (F.floor(i / _BLOCK) + 1).cast("int")) + F.element_at(f"{name}_i", i + 1) + F.char_length(gap)
        near = []
        if words:
            spaced = lambda found: F.lower(F.regexp_replace(found, r"\s++", " "))
            near = [
                spaced(F.regexp_extract(gap, rf"((?<!\S)\S++(?:\s++\S++){{0,{words - 1}}})\s*+$", 1)).alias("left"),
                spaced(F.regexp_extract(F.element_at(gaps, i + 2), rf"^\s*+(\S++(?:\s++\S++){{0,{words - 1}}})", 1)).alias("right"),
            ]
        return F.struct(start.cast("bigint").alias("start"), (start + F.char_length(m)).cast("bigint").alias("end"), m.alias("value"), *near)

    frame = frame.withColumn(name, F.transform(found, place))
    return frame.drop(*(f"{name}_{x}" for x in "mgsboi"))


def digits_of(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def luhn(digits: Column) -> Column:
    """Whether a digit string of sane length passes the check-digit rule."""
    n = F.length(digits)

    def add(total: Column, i: Column) -> Column:
        d = F.substr(digits, i, F.lit(1)).cast("int")
        twice = d * 2
        return total + F.when((n - i) % 2 == 1, F.when(twice > 9, twice - 9).otherwise(twice)).otherwise(d)

    return F.aggregate(F.sequence(F.lit(1), n), F.lit(0), add) % 10 == 0


def _valid(kind: str, value: Column) -> Column:
    if kind == "ip":
        parts = F.transform(F.split(value, r"\."), lambda p: F.ltrim(p, F.lit("0")))  # leading zeros count for nothing
        return F.forall(parts, lambda p: (F.length(p) <= 3) & (F.lpad(p, 3, "0") <= "255"))
    if kind == "card":
        d = digits_of(value)
        return F.when(F.length(d).between(14, 19), luhn(d)).otherwise(False)
    if kind == "phone":
        return F.length(digits_of(value)).between(10, 15)
    return F.lit(True)


def _keeper(kind: str):
    return lambda s: _valid(kind, s["value"])


def base_spans(docs: DataFrame) -> DataFrame:
    """Adds one array column per kind with the valid base matches of ``text``."""
    text = F.col("text")
    hints = {"email": F.contains(text, F.lit("@")), "ip": text.rlike(r"[0-9]\.[0-9]"), "card": text.rlike(r"[0-9][\x20-]?[0-9]"), "phone": F.contains(text, F.lit("+"))}
    for kind in KINDS:
        docs = _placed(docs, kind, PATTERNS[kind], hints[kind])
        docs = docs.withColumn(kind, F.filter(kind, _keeper(kind)))
    return docs


def _joined(spans: Column) -> Column:
    """kind:start:end of sorted (start, rank, end, kind) structs, comma-joined."""
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))))


def _ranked(kind: str, rank: int) -> Column:
    return F.transform(kind, lambda s: F.struct(s["start"].alias("start"), F.lit(rank).alias("rank"), s["end"].alias("end"), F.lit(kind).alias("kind")))


def _keyed(docs: DataFrame) -> DataFrame:
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text")).withColumn("text_key", F.xxhash64("text"))


def _suits(kind: Column, token: Column) -> Column:
    """Whether a token without a base match could be of the kind at all."""
    n = F.length(digits_of(token))
    plain = token.rlike(r"^[^A-Za-z]*$")
    return (
        F.when(kind == "email", token.rlike(r"^[^\s@]+@[^\s@]+$"))
        .when(kind == "ip", (plain & token.rlike(r"[0-9]+([.:_-])[0-9]+\1[0-9]+\1[0-9]+")) | token.rlike(r"^(?=.*[0-9])[0-9A-Fa-f]{0,4}(:[0-9A-Fa-f]{0,4}){2,7}$"))
        .when(kind == "card", plain & n.between(14, 19))
        .otherwise(plain & n.between(7, 15) & token.rlike(r"[\x20().-]"))
    )


def candidate_tokens(docs: DataFrame, words: int) -> DataFrame:
    """(doc_id, text_key, start, end, value, seed, patterns) of identifier-like tokens of keyed documents."""
    frame = _placed(docs, "token", TOKEN, F.col("text").rlike("[0-9@]"), words)
    # Outer, and no filter on the array: a pushed-down filter would repeat its whole derivation per element.
    frame = frame.select("doc_id", "text_key", F.explode_outer("token").alias("t")).where("t.value is not null")
    trimmed = F.regexp_replace("t.value", r"^[^A-Za-z0-9+@(]+|[^A-Za-z0-9)]+$", "")
    left_cut = F.char_length(F.regexp_extract("t.value", r"^[^A-Za-z0-9+@(]+", 0))
    seed = F.lit(None).cast("string")
    for kind in reversed(KINDS):
        match = F.regexp_extract("t.value", PATTERNS[kind], 0)
        seed = F.when((match != "") & _valid(kind, match), F.lit(kind)).otherwise(seed)
    patterns = F.concat(*(F.array(F.concat(F.lit("<"), F.substring_index("t.left", " ", -k)), F.concat(F.lit(">"), F.substring_index("t.right", " ", k))) for k in range(1, words + 1)))
    patterns = F.array_distinct(F.filter(patterns, lambda x: F.length(x) > 1))
    out = frame.select("doc_id", "text_key", (F.col("t.start") + left_cut).alias("start"), trimmed.alias("value"), seed.alias("seed"), patterns.alias("patterns"))
    return out.where("value <> ''").withColumn("end", F.col("start") + F.char_length("value"))


def bootstrap(work: Workspace, tokens: DataFrame, settings: BootstrapSettings) -> DataFrame:
    """Believed (pattern, kind, weight): lexical patterns that keep company with seeds.

    One scalar, the number of unseen instances found so far, reaches the driver a round.
    """
    edges = tokens.select("value", "seed", F.explode("patterns").alias("pattern")).groupBy("pattern", "value").agg(F.max("seed").alias("seed"))
    edges = work.table("edges", edges)
    first = work.table("first_seeds", edges.where("seed is not null").groupBy("value").agg(F.max("seed").alias("known")).withColumn("score", F.lit(1.0)))
    seeds, before = first, 0
    for turn in range(settings.rounds):
        marked = work.table(f"marked{turn}", edges.select("pattern", "value").join(seeds, "value", "left"))
        kinds = marked.where("known is not null").groupBy("pattern", F.col("known").alias("kind")).agg(F.count("*").alias("support")).where(F.col("support") >= settings.support)
        own = F.coalesce(F.col("known") == F.col("kind"), F.lit(False))
        counts = F.when(F.col("known").isNull() & _suits(F.col("kind"), F.col("value")), settings.doubt).otherwise(1.0)
        held = marked.join(kinds, "pattern").groupBy("pattern", "kind").agg(F.sum(F.when(own, F.col("score")).otherwise(0.0)).alias("mass"), F.sum(counts).alias("total"))
        weight = F.col("mass") / (F.col("total") + settings.smoothing)
        believed = work.table(f"believed{turn}", held.select("pattern", "kind", weight.alias("weight")).where(F.col("weight") >= settings.confidence))
        work.drop(f"marked{turn}")
        if turn + 1 == settings.rounds:
            break
        scored = edges.where("seed is null").join(believed, "pattern").where(_suits(F.col("kind"), F.col("value")))
        found = scored.groupBy("value").agg(F.max(F.struct("weight", "kind")).alias("b")).select("value", F.col("b.kind").alias("known"), F.col("b.weight").alias("score"))
        found = work.table(f"found{turn}", found)
        count = found.count()
        if count == before:  # nothing new
            break
        seeds, before = first.unionByName(found), count
    return believed


def discovered(work: Workspace, docs: DataFrame, settings: BootstrapSettings) -> DataFrame:
    """(doc_id, text_key, extra): unseen identifiers of keyed documents as sorted span structs."""
    tokens = work.table("tokens", candidate_tokens(docs, settings.words))
    believed = bootstrap(work, tokens, settings)
    unseen = tokens.where("seed is null").select("doc_id", "text_key", "start", "end", "value", F.explode("patterns").alias("pattern"))
    hits = unseen.join(believed, "pattern").where(_suits(F.col("kind"), F.col("value")))
    best = hits.groupBy("doc_id", "text_key", "start", "end").agg(F.max(F.struct("weight", "kind")).alias("b"))
    rank = F.array_position(F.array(*map(F.lit, KINDS)), F.col("b.kind")).cast("int") - 1
    span = F.struct("start", rank.alias("rank"), "end", F.col("b.kind").alias("kind"))
    return best.select("doc_id", "text_key", span.alias("span")).groupBy("doc_id", "text_key").agg(F.collect_set("span").alias("extra"))


def personal_data(spark: SparkSession, docs: DataFrame, settings: BootstrapSettings = BootstrapSettings()) -> DataFrame:
    """One row per document: counts and digest of base spans, all spans, and the spans as an array.

    Null text counts as empty; documents without matches have zero counts and
    the digest of the empty string; rows are told apart by doc_id (null or not)
    and text, and rows equal in both have equal results; an empty table gives no
    rows; extra columns are ignored, whatever their names.
    """
    work = Workspace(spark, "personal_data")
    keyed = _keyed(docs)
    extra = work.table("extra", discovered(work, keyed, settings))
    based = base_spans(keyed)
    base = F.array_sort(F.concat(*(_ranked(k, i) for i, k in enumerate(KINDS))))
    counts = [F.size(k).cast("long").alias(f"n_{k}") for k in KINDS]
    based = work.table("based", based.select("doc_id", "text_key", *counts, base.alias("base")))
    extra = extra.select(F.col("doc_id").alias("xd"), F.col("text_key").alias("xk"), "extra")
    both = based.join(extra, F.col("doc_id").eqNullSafe(F.col("xd")) & (F.col("text_key") == F.col("xk")), "left")
    free = F.filter("extra", lambda x: ~F.exists("base", lambda b: (b["start"] < x["end"]) & (x["start"] < b["end"])))
    every = F.when(F.col("extra").isNull(), F.col("base")).otherwise(F.array_sort(F.concat("base", free)))
    both = both.withColumn("every", every)
    work.keep("based", "extra")
    return both.select("doc_id", *(f"n_{k}" for k in KINDS), F.sha2(_joined(F.col("base")), 256).alias("base_sha256"), _joined(F.col("every")).alias("spans"), "text_key", F.col("every").alias("found"))


def redact(docs: DataFrame, found: DataFrame, broadcast_bytes: int = 24 << 20) -> DataFrame:
    """Documents (doc_id, text, ...) with every found span replaced by its kind in angle brackets.

    ``found`` is the result of ``personal_data``; lists of at most
    ``broadcast_bytes`` in all are broadcast, so texts are not shuffled.  Overlapping spans merge under
    the first one's kind.  Documents without spans are untouched (null text stays
    null); rows of one doc_id, or without one, are told apart by their text;
    ``n_chars`` follows where there is such a column; other columns, of any name,
    are kept as they are; an empty table stays empty.
    """
    columns = docs.columns
    doc, key, spans, own = (_fresh(columns, x) for x in ("doc", "key", "spans", "own"))
    rows = found.where(F.size("found") > 0).select(F.col("doc_id").alias(doc), F.col("text_key").alias(key), F.col("found").alias(spans)).dropDuplicates([doc, key])
    size = found.agg(F.sum(48 + 96 * F.size("found")).alias("n")).first().n or 0  # bytes of all span lists, at most
    if size <= broadcast_bytes:
        rows = F.broadcast(rows)
    keyed = docs.withColumn(own, F.xxhash64(F.coalesce(F.col("text"), F.lit(""))))
    both = keyed.join(rows, F.col("doc_id").cast("long").eqNullSafe(F.col(doc)) & (F.col(own) == F.col(key)), "left")
    start = F.struct(F.array().cast("array<string>").alias("parts"), F.lit(0).cast("bigint").alias("at"))

    def step(acc: Column, s: Column) -> Column:
        before = F.substr("text", (acc["at"] + 1).cast("int"), F.greatest(s["start"] - acc["at"], F.lit(0)).cast("int"))
        added = F.array(before, F.concat(F.lit("<"), s["kind"], F.lit(">")))
        return F.when(s["start"] < acc["at"], F.struct(acc["parts"].alias("parts"), F.greatest(acc["at"], s["end"]).alias("at"))).otherwise(F.struct(F.concat(acc["parts"], added).alias("parts"), s["end"].alias("at")))

    done = lambda acc: F.concat(F.array_join(acc["parts"], ""), F.substr("text", (acc["at"] + 1).cast("int")))
    cleaned = F.when(F.col(spans).isNull(), F.col("text")).otherwise(F.aggregate(spans, start, step, done))
    both = both.withColumn("text", cleaned)
    if "n_chars" in columns:
        both = both.withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType))
    return both.select(*(F.col(f"`{c}`") for c in columns))


def _fresh(columns: list[str], name: str) -> str:
    """A column name that no column has."""
    taken = {c.lower() for c in columns}
    while name in taken:
        name += "_"
    return name
