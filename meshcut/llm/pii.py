"""Personal data: pattern rules, then bootstrapped contextual extraction of identifiers the rules miss.

The rules find e-mail addresses, IPv4 addresses, payment cards and phone numbers, leftmost and without overlap per kind.
They are the seeds. The words before and after a seed induce lexical patterns (left word; left and right word); every
token that holds an at sign or six digits, seed or not, is an instance of the patterns around it. Scores go back and forth on
this graph: an instance's confidence for a kind is 1 for a seed of it and else 1 - prod(1 - confidence) over its patterns; a
pattern's is the sum over its distinct instances, divided by that sum, the seeds of other kinds only, `doubt` times what is
missing to 1 in the instances that are no seeds, and one more. So tokens never seen before weigh little against a pattern
until it is known what they are, and a pattern gains as others vouch for its instances. After `rounds` rounds, patterns of
at least `least_seeds` distinct seeds and `least_confidence` mark the other instances beside them as spans of the kind, the
first kind of KINDS if several do. Base spans always stay; tokens that overlap one are no instances.

Everything is native. The regular expressions start only at the first character of a run and take runs whole, so they are
linear in the text, and repeats are of single characters, so long chains need no deep stack: separators inside a chain are
first replaced by a control character of the same width. Texts are read once; only spans and contexts are shuffled.
A null text is empty, as is one without a digit or an at sign; texts are taken whole, and the time is linear in their length
but for sorting their spans; a null id is an id like others; rows that repeat an id are told apart by text, and identical
rows get identical results. Columns other than doc_id and text are ignored, whatever they are called.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from meshcut.llm import common

KINDS = ("email", "ip", "card", "phone")
#: Stand for a dot inside a domain and for a separator inside a chain of digits.
DOT, GAP = "\x03", "\x01"
LOCAL = rf"[A-Za-z0-9._%+{DOT}-]"
EMAIL = rf"(?:\G|(?<!{LOCAL})){LOCAL}++@[A-Za-z0-9-]++{DOT}[A-Za-z0-9{DOT}-]++"
IP = r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"
CARD = rf"[0-9][0-9{GAP}]++"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
TOKEN = r"(?<![^\x20\x09-\x0D])[^\x20\x09-\x0D0-9@]*+[0-9@][^\x20\x09-\x0D]*+"
BLOCK = 128


def digits_of(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]+", "")


def valid(kind: str, x: Column) -> Column:
    if kind == "ip":
        part = lambda p: F.ltrim(p, F.lit("0"))
        return F.forall(F.split(x, r"\."), lambda p: (F.length(part(p)) <= 3) & (F.coalesce(part(p).try_cast("int"), F.lit(0)) <= 255))
    if kind == "card":
        return F.length(digits_of(x)).between(12, 19) & F.call_function("luhn_check", digits_of(x))
    if kind == "phone":
        return F.length(digits_of(x)).between(9, 15)
    return F.lit(True)


def with_places(df: DataFrame, found: list[str]) -> DataFrame:
    """For each name, arrays name_m (matches) and name_p (pieces between): adds name_s, the matches' starts.

    The running sum is taken in blocks, so it stays near linear in the number of matches.
    """
    zero = F.lit(0)
    total = lambda part: F.aggregate(part, zero, lambda a, x: a + x)
    block = lambda i: F.floor(i / BLOCK).cast("int")

    def widths(k):
        return F.transform(f"{k}_m", lambda x, i: F.length(x) + F.length(F.get(f"{k}_p", i)))

    def blocks(k):
        sums = F.transform(F.sequence(zero, block(F.size(f"{k}_l") - 1)), lambda b: total(F.slice(f"{k}_l", b * BLOCK + 1, BLOCK)))
        return F.when(F.size(f"{k}_l") > 0, sums).otherwise(F.array().cast("array<int>"))

    def before(k):
        return F.transform(f"{k}_b", lambda x, b: F.when(F.size(f"{k}_b") > 0, total(F.slice(f"{k}_b", F.lit(1), b))))

    def starts(k):
        at = F.transform(f"{k}_m", lambda x, i: F.get(f"{k}_c", block(i)) + total(F.slice(f"{k}_l", block(i) * BLOCK + 1, i % BLOCK)) + F.length(F.get(f"{k}_p", i)))
        return F.when(F.size(f"{k}_c") > 0, at).otherwise(F.array().cast("array<int>"))

    for suffix, make in (("l", widths), ("b", blocks), ("c", before), ("s", starts)):
        df = df.withColumns({f"{k}_{suffix}": make(k) for k in found})
    return df.drop(*(f"{k}_{x}" for k in found for x in "lbc"))


def context(pieces: str, i: Column) -> tuple[Column, Column]:
    """The word before and the word after match i; a neighbour that is a match itself is <id>."""
    left = F.regexp_extract(F.right(F.get(pieces, i), F.lit(64)), r"([^\x20\x09-\x0D]+)[\x20\x09-\x0D]*$", 1)
    right = F.regexp_extract(F.left(F.get(pieces, i + 1), F.lit(64)), r"^[\x20\x09-\x0D]*([^\x20\x09-\x0D]+)", 1)
    name = lambda x: F.lower(F.when(x == "", F.lit("<id>")).otherwise(x))
    return name(left), name(right)


def scanned(docs: DataFrame, *keep: Column) -> DataFrame:
    """keep, base (spans by start and kind: s, k, e), seeds and others (kind, start, end, instance, left, right)."""
    text = F.translate(F.coalesce(F.col("text"), F.lit("")), DOT + GAP, "\x02\x02")
    df = docs.select(*keep, F.when(text.rlike("[0-9@]"), text).otherwise(F.lit("")).alias("_text"))
    df = df.withColumns({
        "email_t": F.when(F.col("_text").contains("@"), F.regexp_replace("_text", r"(?<=[A-Za-z0-9-])\.(?=[A-Za-z0-9-])", DOT)).otherwise(F.lit("")),
        "card_t": F.regexp_replace("_text", r"(?<=[0-9])[\x20-](?=[0-9])", GAP),
    })
    source = {"email": ("email_t", EMAIL), "ip": ("_text", IP), "card": ("card_t", CARD), "phone": ("_text", PHONE), "token": ("_text", TOKEN)}
    df = df.withColumns({f"{k}_m": F.regexp_extract_all(t, F.lit(p), 0) for k, (t, p) in source.items()} | {f"{k}_p": F.split(t, p) for k, (t, p) in source.items()})
    df = with_places(df.drop("_text", "email_t", "card_t"), list(source))
    rows = {}

    def rows_of(rank, k):
        def row(x, i):
            left, right = context(f"{k}_p", i)
            start = F.get(f"{k}_s", i)
            return F.struct(start.alias("s"), F.lit(rank).alias("k"), (start + F.length(x)).alias("e"), valid(k, x).alias("ok"), F.xxhash64(F.lower(x)).alias("inst"), left.alias("left"), right.alias("right"))
        return F.filter(F.transform(f"{k}_m", row), lambda r: r["ok"])

    for rank, k in enumerate(KINDS):
        rows[f"{k}_r"] = rows_of(rank, k)
    df = df.withColumns(rows)
    df = df.withColumn("_seeds", F.concat(*rows)).withColumn("_base", F.sort_array(F.transform("_seeds", lambda r: F.struct(r["s"], r["k"], r["e"]))))

    def other(x, i):
        left, right = context("token_p", i)
        start = F.get("token_s", i)
        trimmed = F.regexp_replace(x, r"^[^A-Za-z0-9@+]+|[^A-Za-z0-9]+$", "")
        lead = F.length(x) - F.length(F.regexp_replace(x, r"^[^A-Za-z0-9@+]+", ""))
        return F.struct((start + lead).alias("s"), F.lit(-1).alias("k"), (start + lead + F.length(trimmed)).alias("e"), ((F.length(digits_of(x)) >= 6) | F.contains(x, F.lit("@"))).alias("ok"), F.xxhash64(F.lower(trimmed)).alias("inst"), left.alias("left"), right.alias("right"))

    others = F.filter(F.transform("token_m", other), lambda r: r["ok"])
    df = df.withColumn("_others", F.when(F.size("token_s") > 0, others))
    kept = [c for c in df.columns if not any(c.startswith(f"{k}_") for k in source)]
    return df.select(*kept)


def patterns_of(r: Column) -> Column:
    return F.array(F.concat(F.lit("L "), r["left"]), F.concat(F.lit("B "), r["left"], F.lit(" | "), r["right"]))


def confident_patterns(graph: DataFrame, rounds: int, least_seeds: int, least_confidence: float, doubt: float) -> DataFrame:
    """graph: distinct (pattern, inst, k); k is the kind of a seed, -1 of others. Gives (pattern, kind)."""
    seeds = graph.where("k >= 0").distinct()
    known = seeds.select("inst", "k").distinct()
    # an instance that is a seed anywhere is one for all its patterns
    edges = graph.select("pattern", "inst").distinct().join(known.select("inst").distinct().withColumn("_known", F.lit(1)), "inst", "left")
    edges = edges.select("pattern", "inst", F.coalesce("_known", F.lit(0)).alias("_known"))
    backed = seeds.groupBy("pattern", "k").agg(F.count("*").alias("backing")).where(F.col("backing") >= least_seeds)
    edges = common.written(edges.join(backed.select("pattern").distinct(), "pattern", "left_semi"), "pii-edges")
    size = common.written(edges.groupBy("pattern").agg(F.sum("_known").alias("n_known"), F.sum(1 - F.col("_known")).alias("n_new")), "pii-sizes")
    belief = known.withColumn("c", F.lit(1.0))
    score = None
    for _ in range(rounds):
        sums = edges.join(belief, "inst").groupBy("pattern", "k").agg(F.sum(F.col("c") * F.col("_known")).alias("seeds"), F.sum(F.col("c") * (1 - F.col("_known"))).alias("new"))
        score = sums.join(size, "pattern").join(backed, ["pattern", "k"])
        good = F.col("seeds") + F.col("new")
        against = (F.col("n_known") - F.col("seeds")) + doubt * (F.col("n_new") - F.col("new")) + 1
        score = common.written(score.select("pattern", "k", (good / (good + against)).alias("confidence")), "pii-patterns")
        raised = edges.where("_known = 0").join(score, "pattern").groupBy("inst", "k").agg((1 - F.exp(F.sum(F.log(1 - F.least("confidence", F.lit(0.999)))))).alias("c"))
        belief = common.written(known.withColumn("c", F.lit(1.0)).unionByName(raised), "pii-belief")
    return score.where(F.col("confidence") >= least_confidence).select("pattern", "k")


def apart(marks: DataFrame) -> DataFrame:
    """marks (doc_id, _th, r) without the tokens that overlap a base span of their text."""
    mine = Window.partitionBy("doc_id", "_th").orderBy(F.col("r.s"), F.col("r.k"), F.col("r.e"))
    base = F.col("r.k") >= 0
    reached = F.max(F.when(base, F.col("r.e"))).over(mine.rowsBetween(Window.unboundedPreceding, -1))
    following = F.min(F.when(base, F.col("r.s"))).over(mine.rowsBetween(1, Window.unboundedFollowing))
    free = F.coalesce(F.col("_reached") <= F.col("r.s"), F.lit(True)) & F.coalesce(F.col("_next") >= F.col("r.e"), F.lit(True))
    return marks.withColumns({"_reached": reached, "_next": following}).where(base | free).drop("_reached", "_next")


def personal_data(docs: DataFrame, rounds: int = 3, least_seeds: int = 5, least_confidence: float = 0.8, doubt: float = 0.25) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base and spans (arrays of s, k, e) of every row."""
    common.prepare(docs.sparkSession)
    rows = common.written(scanned(docs, F.col("doc_id"), common.text_hash().alias("_th")), "pii")
    place = F.explode(F.concat("_seeds", F.coalesce("_others", F.expr("filter(_seeds, x -> false)"))))
    marks = rows.where("size(_seeds) > 0 or size(_others) > 0").select("doc_id", "_th", place.alias("r"))
    marks = common.written(apart(marks), "pii-marks")
    graph = marks.select(F.explode(patterns_of(F.col("r"))).alias("pattern"), F.col("r.inst").alias("inst"), F.col("r.k").alias("k")).distinct()
    good = confident_patterns(common.written(graph, "pii-graph"), rounds, least_seeds, least_confidence, doubt)
    loose = marks.where("r.k < 0")
    hits = loose.select("doc_id", "_th", "r.s", "r.e", F.explode(patterns_of(F.col("r"))).alias("pattern")).join(good, "pattern")
    found = hits.groupBy("doc_id", "_th", "s", "e").agg(F.min("k").alias("k")).groupBy("doc_id", "_th").agg(F.collect_set(F.struct("s", "k", "e")).alias("_more"))
    out = rows.select("doc_id", "_th", "_base").join(found.withColumnsRenamed({"doc_id": "_d", "_th": "_t"}), F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("_th") == F.col("_t")), "left")
    count = lambda n: F.size(F.filter("_base", lambda b: b["k"] == n)).cast("long")
    counts = [count(n).alias(f"n_{k}") for n, k in enumerate(KINDS)]
    return out.select("doc_id", *counts, F.col("_base").alias("base"), F.sort_array(F.when(F.col("_more").isNotNull(), F.concat("_base", "_more")).otherwise(F.col("_base"))).alias("spans"))


def span_text(spans: str) -> Column:
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda r: F.concat_ws(":", F.get(names, r["k"]), r["s"], r["e"])), ",")


def pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = personal_data(common.table(spark, sf_dir, "documents"))
    return found.select("doc_id", *(f"n_{k}" for k in KINDS), F.sha2(span_text("base").cast("binary"), 256).alias("base_sha256"), span_text("spans").alias("spans"))
