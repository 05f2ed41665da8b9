"""Information-theoretic sanitisation of personal data, DataFrame functions only.

Protected entities are e-mail addresses, IP numbers, payment cards and phone
numbers, found by four fixed patterns.  Corpus counts then estimate how much a
term reveals of an entity: with n(t), n(e), n(t, e) the documents that hold the
term, the entity, and both, wherever they stand in them,

    p(e | t) = (n(t, e) + prior * n(e) / N) / (n(t) + prior),
    pmi(t; e) = log2(p(e | t) * N / n(e)),   share = pmi / log2(N / n(e)).

A share of 1 means that the term names the entity as well as the entity itself.
``prior`` documents of the entity's base rate stand in for what was not seen, so
that entities of one or two documents are judged too, with no least count.
Terms with ``share >= disclosure`` are removed (or generalised to their kind)
at every place of every text, also where the entity itself does not stand.

Defined results: null text is empty; matches are leftmost and do not overlap
within a kind, a match that fails its check is dropped without a retry; offsets
count code points, ends exclusive; every row is a document of its own, also one
that repeats an id or has none, and gets the spans of its own text; empty tables
give empty results; other columns than id and text are not read.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from stablecf.llm.common import id_back, ids_and_texts, staged

# fixed values: kinds in output order.  The patterns are those of the contract, written without backtracking:
# a match starts where the last one ended (\G) or where its first run of characters starts.
KINDS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++(?:\.[0-9]++)(?:\.[0-9]++)(?:\.[0-9]++)",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
HINTS = {"email": "@", "ip": ".", "card": None, "phone": "+"}
CHARACTER = r"[0-9A-Za-z\x{80}-\x{10FFFF}]"
TERM = CHARACTER + "{4,}+"
#: Marks before and after a match while its place is worked out; no pattern has a control character.
OPEN, CLOSE, OTHER = "\x01", "\x02", "\x03"
NONE = "cast(array() as array<struct<at:int, value:string>>)"


def _luhn(digits: Column) -> Column:
    n = F.length(digits)

    def value(i: Column) -> Column:
        v = F.substr(digits, i, F.lit(1)).cast("int") * (F.lit(1) + F.pmod(n - i, F.lit(2)))
        return F.when(v > 9, v - 9).otherwise(v)

    return F.pmod(F.aggregate(F.sequence(F.lit(1), n), F.lit(0), lambda a, i: a + value(i)), F.lit(10)) == 0


def _valid(kind: str, m: Column) -> Column:
    digits = F.regexp_replace(m, "[^0-9]", "")
    if kind == "ip":
        return F.forall(F.split(m, r"\."), lambda p: F.regexp_replace(p, "^0+(?=[0-9])", "").rlike("^(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])$"))
    if kind == "card":
        return F.when(F.length(digits).between(12, 19), _luhn(digits)).otherwise(False)
    if kind == "phone":
        return F.length(digits).between(9, 15)
    return F.lit(True)


def _pieces(text: str, pattern: str | Column) -> Column:
    """The text cut before each match; a piece after the first is a match, a mark and what follows it.  One pass of the pattern."""
    pattern = F.lit(pattern) if isinstance(pattern, str) else pattern
    own = F.col(text).contains(OPEN) | F.col(text).contains(CLOSE)
    plain = F.when(own, F.translate(text, OPEN + CLOSE, OTHER + OTHER)).otherwise(F.col(text))
    return F.split(F.regexp_replace(plain, pattern, F.lit(OPEN + "$0" + CLOSE)), OPEN, -1)


def _blocks(items: str, size: int = 256) -> Column:
    """An array in runs of ``size``: what is added up along a long text is added up by runs first, so that no step copies the whole."""
    last = F.floor((F.size(items) - 1) / size).cast("int")
    return F.when(F.size(items) > 0, F.transform(F.sequence(F.lit(0), last), lambda b: F.slice(items, b * size + 1, F.lit(size))))


def _carried(totals: Column, first: Column, join: Callable[[Column, Column], Column]) -> Column:
    """What holds before each run, given each run's own total."""
    return F.aggregate(totals, F.array(first), lambda a, x: F.concat(a, F.array(join(F.element_at(a, -1), x))))


def with_places(df: DataFrame, pieces: str, name: str) -> DataFrame:
    """Adds array<struct(at, value)> of the matches in ``pieces``, a column of its own so that the pattern runs once."""

    def step(acc: Column, piece: Column) -> Column:
        value = F.substring_index(piece, CLOSE, 1)
        return F.struct((acc["end"] + F.length(piece) - 1).alias("end"), F.concat(acc["out"], F.array(F.struct(acc["end"].alias("at"), value.alias("value")))).alias("out"))

    def run(x: Column, at: Column) -> Column:
        return F.aggregate(x, F.struct(at.alias("end"), F.expr(NONE).alias("out")), step, lambda a: a["out"])

    out = df.withColumn("_rest", F.when(F.size(pieces) > 1, F.slice(pieces, F.lit(2), F.size(pieces))))
    out = out.withColumn("_runs", _blocks("_rest"))
    sums = F.transform("_runs", lambda x: F.aggregate(x, F.lit(0), lambda a, p: a + F.length(p) - 1))
    out = out.withColumn("_at", _carried(sums, F.length(F.col(pieces)[0]), lambda a, x: a + x))
    found = F.flatten(F.zip_with("_runs", F.slice("_at", F.lit(1), F.size("_runs")), run))
    return out.withColumn(name, F.coalesce(found, F.expr(NONE))).drop("_rest", "_runs", "_at")


def base_spans(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` with their spans: structs (start, k, end, kind, value) in order."""
    out, names = docs, docs.columns
    for k in KINDS:
        may = F.col("text").contains(HINTS[k]) if HINTS[k] else F.col("text").rlike("[0-9](?:[\\x20-]?[0-9]){11}")
        if k in ("ip", "phone"):
            may = may & F.col("text").rlike("[0-9]")
        out = out.withColumn(k, F.when(may, _pieces("text", KINDS[k])))
    for k in KINDS:
        out = with_places(out, k, k)
    return out.select(*names, F.array_sort(F.concat(*(_spans_of(k) for k in KINDS))).alias("spans"))


def _spans_of(kind: str) -> Column:
    i = list(KINDS).index(kind)
    ok = F.filter(F.col(kind), lambda x: _valid(kind, x["value"]))
    return F.transform(ok, lambda x: F.struct(x["at"].alias("start"), F.lit(i).alias("k"), (x["at"] + F.length(x["value"])).alias("end"), F.lit(kind).alias("kind"), x["value"].alias("value")))


def words_of(text: str) -> Column:
    """The different words of a text that may be terms, as they are written."""
    return F.array_distinct(F.regexp_extract_all(text, F.lit(TERM), F.lit(0)))


def terms_of(words: str) -> Column:
    """Different words as different terms, in lower case (no word holds the blank that joins them here)."""
    return F.when(F.size(words) > 0, F.array_distinct(F.split(F.lower(F.concat_ws(" ", words)), " "))).otherwise(F.expr("cast(array() as array<string>)"))


def sieve(spark: SparkSession, keys: DataFrame, key: str) -> Callable[[Column], Column]:
    """A test that every value of ``key`` passes, and of other values at most about one in 16 while there are under 4 million keys.

    It only thins rows before a join on the keys.  The bits are one array, 8 MB at most, built from rows of 4096 longs.
    """
    bits = min(1 << 26, max(1 << 16, 1 << (16 * keys.count()).bit_length()))
    bit = lambda c: F.pmod(F.xxhash64(c), F.lit(bits))
    word = lambda c: F.shiftright(bit(c), 6).cast("int")
    mask = lambda c: F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod(bit(c), F.lit(64)).cast("int"))
    words = keys.select(word(F.col(key)).alias("w"), mask(F.col(key)).alias("b")).groupBy("w").agg(F.bit_or("b").alias("b"))
    words = spark.range(bits >> 6).select(F.col("id").cast("int").alias("w")).join(words, "w", "left").select("w", F.coalesce("b", F.lit(0).cast("long")).alias("b"))
    parts = words.groupBy(F.shiftright("w", 12).alias("p")).agg(F.transform(F.array_sort(F.collect_list(F.struct("w", "b"))), lambda x: x["b"]).alias("bs"))
    whole = staged(spark, parts.agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("p", "bs"))), lambda x: x["bs"])).alias("bits")), "pii-sieve").scalar()
    return lambda c: whole[word(c)].bitwiseAND(mask(c)) != 0


def share(total: int, prior: float) -> Column:
    """What the term tells of the entity, as a share of the entity's information; of (nt, ne, nte)."""
    given = (F.col("nte") + F.lit(prior) * F.col("ne") / F.lit(float(total))) / (F.col("nt") + F.lit(prior))
    info = F.log2(F.lit(float(total)) / F.col("ne"))
    return (F.log2(given) + info) / info


def leaking_terms(spark: SparkSession, placed: DataFrame, total: int, disclosure: float, prior: float) -> DataFrame:
    """(term): the terms that reveal some entity, by counts over whole documents; ``placed``: row, words, spans."""
    entities = F.array_distinct(F.transform("spans", lambda s: F.concat_ws(":", s["kind"], F.lower(s["value"]))))
    has = placed.where(F.size("spans") > 0).select("words", entities.alias("entities"))
    ne = staged(spark, has.select(F.explode("entities").alias("entity")).groupBy("entity").agg(F.count(F.lit(1)).alias("ne")).where(F.col("ne") < total), "pii-entities")
    most = ne.agg(F.max("ne")).first()[0]
    if most is None:
        return staged(spark, has.select(F.lit("").alias("term")).where("false"), "pii-leaks")
    # nte <= ne, so a term of more documents than this reveals nothing: no pair of it is made
    limit = lambda ne: F.pow(F.lit(float(total)) / ne, F.lit(1 - disclosure)) * ne * (1 + prior / total) - F.lit(prior) + 1e-6
    nt = placed.select(F.explode(terms_of("words")).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("nt"))
    nt = staged(spark, nt.where(F.col("nt") <= limit(F.lit(float(most)))), "pii-rare-terms")
    pairs = has.select("entities", F.explode(terms_of("words")).alias("term")).join(nt, "term").select("term", "nt", F.explode("entities").alias("entity"))
    pairs = pairs.join(ne, "entity").where(F.col("nt") <= limit(F.col("ne")))
    pairs = pairs.groupBy("entity", "term", "nt", "ne").agg(F.count(F.lit(1)).alias("nte"))
    return staged(spark, pairs.where(share(total, prior) >= F.lit(disclosure)).select("term").distinct(), "pii-leaks")


def sanitise(
    spark: SparkSession,
    df: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    disclosure: float = 0.8,
    prior: float = 2.0,
    generalise: bool = True,
    with_text: bool = True,
) -> DataFrame:
    """(doc_id, spans[, sanitised]): base spans and the method's ``term`` spans; the text with each span replaced by its kind or removed."""
    docs = ids_and_texts(df, id_col, text_col)
    # a row is known by its id and text: rows that agree in both have the same spans
    docs = docs.select(F.xxhash64("doc_id", "text").alias("row"), "doc_id", "text")
    # words are taken from the texts again where they are needed: that costs less than storing them
    placed = staged(spark, base_spans(docs), "pii-placed").withColumn("words", words_of("text"))
    total = max(1, placed.count())
    leaks = leaking_terms(spark, placed, total, disclosure, prior)
    passes = sieve(spark, leaks, "term")
    # words as they are written, so that a pattern of them finds a document's places without regard to case rules
    words = placed.select("row", F.explode("words").alias("word")).select("row", "word", F.lower("word").alias("term")).where(passes(F.col("term"))).join(leaks, "term")
    words = words.groupBy("row").agg(F.collect_set("word").alias("leaking"))
    out = placed.select("row", "doc_id", "text", "spans").join(words, "row", "left")
    pattern = F.concat(F.lit(f"(?<!{CHARACTER})(?:"), F.array_join("leaking", "|"), F.lit(f")(?!{CHARACTER})"))
    out = out.withColumn("pieces", F.when(F.col("leaking").isNotNull(), _pieces("text", pattern)))
    out = with_places(out, "pieces", "placed")
    more = F.transform("placed", lambda x: F.struct(x["at"].alias("start"), F.lit(len(KINDS)).alias("k"), (x["at"] + F.length(x["value"])).alias("end"), F.lit("term").alias("kind"), F.lower(x["value"]).alias("value")))
    # a term inside a base span is covered by it already
    extra = F.filter(more, lambda t: ~F.exists("spans", lambda s: (t["start"] < s["end"]) & (s["start"] < t["end"])))
    out = out.select("doc_id", "text", "spans", F.array_sort(F.concat("spans", extra)).alias("all_spans"))
    if not with_text:
        return out.select(id_back(), F.col("spans").alias("base"), F.col("all_spans").alias("spans"))
    label = lambda s: F.concat(F.lit("["), F.upper(s["kind"]), F.lit("]")) if generalise else F.lit("")

    def cut(acc: Column, s: Column) -> Column:
        gap = F.substr("text", acc["end"] + 1, F.greatest(s["start"] - acc["end"], F.lit(0)))
        new = F.when(s["start"] >= acc["end"], F.concat(acc["out"], gap, label(s))).otherwise(acc["out"])
        return F.struct(F.greatest(acc["end"], s["end"]).alias("end"), new.alias("out"))

    def run(x: Column, at: Column) -> Column:
        return F.aggregate(x, F.struct(at.alias("end"), F.lit("").alias("out")), cut, lambda a: a["out"])

    out = out.withColumn("_runs", _blocks("all_spans"))
    last = F.transform("_runs", lambda x: F.aggregate(x, F.lit(0), lambda a, s: F.greatest(a, s["end"])))
    out = out.withColumn("_at", _carried(last, F.lit(0), F.greatest))
    parts = F.zip_with("_runs", F.slice("_at", F.lit(1), F.size("_runs")), run)
    clean = F.coalesce(F.concat(F.array_join(parts, ""), F.substr("text", F.element_at("_at", -1) + 1, F.length("text"))), F.col("text"))
    return out.select(id_back(), F.col("spans").alias("base"), F.col("all_spans").alias("spans"), clean.alias("sanitised"))


def digest(found: DataFrame) -> DataFrame:
    text = lambda c: F.array_join(F.transform(c, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    count = lambda k: F.size(F.filter("base", lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    counts = [count(k) for k in KINDS]
    return found.select("doc_id", *counts, F.sha2(text("base"), 256).alias("base_sha256"), text("spans").alias("spans"))
