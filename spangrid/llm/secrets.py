"""Secret scans: fixed patterns, and character Markov models of random strings against ordinary identifiers.

Everything runs as DataFrame expressions. Two first-order Markov chains over 67 characters are fitted by counting
bigrams of labelled strings: random ones come from a seeded generator (hexadecimal, base 64, upper-case
alphanumeric), ordinary ones are the words of a bounded sample of labelled documents, alone and joined as
identifiers are (``one_two``, ``oneTwo``, ``one2``). The difference of the two chains' log-probabilities is one
67 x 67 table of literals, so a scan needs no join. A run of 16 or more such characters is a find if it
mixes letters and digits and its log-likelihood ratio exceeds both limits below.

Positions are code points, end exclusive. ``split`` gives the pieces between a pattern's matches and
``regexp_extract_all`` the matches; running sums of their lengths are the positions.

Results by case: null and empty texts have no spans; repeated rows and null ids give one row each; a find of
the models that touches a find of the patterns is left out, as that one stays.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Kinds in order with their patterns, and the least length of what counts.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{12,}"
HEX = r"[0-9a-f]{32,}"
KINDS = ("assign", "access", "hex", "random")

ALPHABET = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_=-"
RUN = r"[A-Za-z0-9+/_=-]{16,}"
#: Documents whose words stand for ordinary identifiers, and generated random strings of each form.
SAMPLE_DOCUMENTS, SAMPLE_RANDOM = 400, 4000
#: Natural-log likelihood ratio that a find exceeds in all, and for each step of the chain.
LEAST_RATIO, LEAST_STEP = 20.0, 0.6


def _bigrams(strings: DataFrame) -> DataFrame:
    """(g, n): counts of the character pairs in the column ``s``."""
    pairs = F.transform(F.sequence(F.lit(1), F.length("s") - 1), lambda i: F.substring(F.col("s"), i, F.lit(2)))
    return strings.filter(F.length("s") >= 2).select(F.explode(pairs).alias("g")).groupBy("g").agg(F.count("*").alias("n"))


def random_strings(spark, n: int, seed: int = 0) -> DataFrame:
    """Labelled random strings from a generator: column ``s``."""
    h = F.sha2(F.concat_ws(":", F.lit(seed), "id").cast("binary"), 256)
    raw = F.unhex(h)
    upper = F.translate(F.regexp_replace(F.base64(raw), "[+/=]", ""), "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ")
    return spark.range(n).select(F.explode(F.array(F.substring(h, 1, 40), F.translate(F.base64(raw), "=", ""), upper)).alias("s"))


def ordinary_strings(docs: DataFrame, labels: DataFrame, n: int) -> DataFrame:
    """Words of n labelled documents (those first in the order of a hash), and identifiers joined from them."""
    known = labels.select(F.col("doc_id").alias("_d")).filter("_d is not null").distinct().orderBy(F.xxhash64("_d"), "_d").limit(n)
    some = docs.select("doc_id", "text").join(F.broadcast(known), F.col("doc_id") == F.col("_d"), "left_semi")  # n ids
    words = F.array_distinct(F.regexp_extract_all(F.coalesce("text", F.lit("")), F.lit(r"([A-Za-z][a-z]+|[0-9]{1,4})"), F.lit(1)))
    w = some.select(words.alias("w")).filter(F.size("w") > 1)
    pair = lambda f: F.transform(F.sequence(F.lit(1), F.size("w") - 1), lambda i: f(F.element_at("w", i), F.element_at("w", i + 1)))
    joined = F.concat(
        F.col("w"), pair(lambda a, b: F.concat(F.lower(a), F.lit("_"), F.lower(b))), pair(lambda a, b: F.concat(a, F.initcap(b))),
        pair(lambda a, b: F.concat(F.lower(a), F.lit("-"), b)), F.transform("w", lambda a: F.concat(a, F.length(a).cast("string"))),
    )
    return w.select(F.explode(joined).alias("s"))


def fit(docs: DataFrame, labels: DataFrame) -> list[float]:
    """log P(second | first) under the random chain less that under the ordinary one, line by line of the alphabet."""
    both = _bigrams(random_strings(docs.sparkSession, SAMPLE_RANDOM)).withColumn("k", F.lit(1)).unionByName(
        _bigrams(ordinary_strings(docs, labels, SAMPLE_DOCUMENTS)).withColumn("k", F.lit(0))
    )
    size = len(ALPHABET)
    at = {c: i for i, c in enumerate(ALPHABET)}
    table = [[0.5] * (size * size) for _ in range(2)]
    for g, n, k in both.filter(F.col("g").rlike(r"^[A-Za-z0-9+/_=-]{2}$")).collect():  # at most 2 x 67 x 67 rows
        table[k][at[g[0]] * size + at[g[1]]] += n
    total = [[sum(t[i * size : (i + 1) * size]) for i in range(size)] for t in table]
    return [math.log(table[1][i] / total[1][i // size]) - math.log(table[0][i] / total[0][i // size]) for i in range(size * size)]


def ratio(s: Column, model: list[float]) -> Column:
    """The log-likelihood ratio of a string of the alphabet."""
    values, letters, size = F.array(*[F.lit(round(x, 4)) for x in model]), F.lit(ALPHABET), len(ALPHABET)
    code = lambda i: F.instr(letters, F.substring(s, i, F.lit(1)))
    step = lambda acc, i: acc + F.element_at(values, ((code(i) - 1) * size + code(i + 1)).cast("int"))
    return F.aggregate(F.sequence(F.lit(1), F.length(s) - 1), F.lit(0.0), step)


_SPAN = "array<struct<start:int,k:int,stop:int,s:string>>"


def _spans(text: Column, pattern: str, kind: int, keep) -> Column:
    """Sorted spans of a pattern's matches m for which keep(m, group 2) holds, where there is any."""
    gaps = F.split(text, pattern, -1)
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    value = F.regexp_extract_all(text, F.lit(pattern), F.lit(2)) if kind == 0 else found
    triples = F.arrays_zip(F.slice(gaps, F.lit(1), F.size(found)).alias("gap"), found.alias("m"), value.alias("v"))
    start = F.struct(F.lit(0).alias("at"), F.array().cast(_SPAN).alias("out"))

    def step(acc: Column, x: Column) -> Column:
        a = acc["at"] + F.length(x["gap"])
        b = a + F.length(x["m"])
        span = F.struct(a.alias("start"), F.lit(kind).alias("k"), b.alias("stop"), x["m"].alias("s"))
        return F.struct(b.alias("at"), F.when(keep(x["m"], x["v"]), F.concat(acc["out"], F.array(span))).otherwise(acc["out"]).alias("out"))

    return F.when(text.rlike(pattern), F.aggregate(triples, start, step, lambda acc: acc["out"])).otherwise(F.array().cast(_SPAN))


def scan(docs: DataFrame, model: list[float]) -> DataFrame:
    """docs (any columns, with ``text``) and, in ``_base`` and ``_added``, its spans: structs of start, k (of KINDS), stop and s."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    always = lambda m, v: F.lit(True)
    out = docs.withColumn("_assign", _spans(text, ASSIGN, 0, lambda m, v: F.length(v) >= 8)).withColumn("_access", _spans(text, ACCESS, 1, always)).withColumn("_hex", _spans(text, HEX, 2, always))
    mixed = rf"(?=[A-Za-z0-9+/_=-]*[0-9])(?=[A-Za-z0-9+/_=-]*[A-Za-z]){RUN}"
    likely = lambda m, v: ratio(m, model) >= F.greatest(F.lit(LEAST_RATIO), (F.length(m) - 1) * LEAST_STEP)
    out = out.withColumn("_random", _spans(text, mixed, 3, likely)).withColumn("_base", F.concat("_assign", "_access", "_hex"))
    free = F.filter("_random", lambda r: ~F.exists("_base", lambda b: (b["start"] < r["stop"]) & (r["start"] < b["stop"])))
    return out.withColumn("_added", F.when(F.size("_random") > 0, free).otherwise(F.col("_random"))).drop("_random")


def _listed(spans: Column) -> Column:
    name = F.array(*map(F.lit, KINDS))
    one = lambda x: F.concat_ws(":", F.element_at(name, x["k"] + 1), x["start"], x["stop"])
    return F.when(F.size(spans) > 0, F.array_join(F.transform(F.array_sort(spans), one), ",")).otherwise(F.lit(""))


def spans_of_documents(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Per document the counts and digest of the patterns' finds, and all spans."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    out = scan(rows, fit(rows, labels))
    return out.select(
        "doc_id", F.size("_assign").cast("long").alias("n_assign"), F.size("_access").cast("long").alias("n_access"), F.size("_hex").cast("long").alias("n_hex"),
        F.sha2(_listed(F.col("_base")).cast("binary"), 256).alias("base_sha256"), _listed(F.concat("_base", "_added")).alias("spans"), F.size("_added").cast("long").alias("n_added"),
    )


def redact(docs: DataFrame, labels: DataFrame, mark: str = "[secret]") -> DataFrame:
    """docs, every column kept, with each stretch of text that finds cover replaced by ``mark``."""
    names = ["text" if c == "text" else f"x{i}" for i, c in enumerate(docs.columns)]  # so that no column is taken for a find
    out = scan(docs.toDF(*names), fit(docs.select("doc_id", "text"), labels))
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    begin = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def step(acc: Column, x: Column) -> Column:
        fresh = x["start"] >= acc["at"]
        piece = F.concat(acc["out"], F.substring(text, acc["at"] + 1, x["start"] - acc["at"]), F.lit(mark))
        return F.struct(F.greatest(acc["at"], x["stop"]).alias("at"), F.when(fresh, piece).otherwise(acc["out"]).alias("out"))

    spans = F.array_sort(F.concat("_base", "_added"))
    clean = F.aggregate(spans, begin, step, lambda acc: F.concat(acc["out"], F.substring(text, acc["at"] + 1, F.length(text))))
    return out.withColumn("text", F.when(F.size(spans) > 0, clean).otherwise(F.col("text"))).select(*names).toDF(*docs.columns)
