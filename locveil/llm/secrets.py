"""Secret scans with multipart credential linking, in Spark expressions only.

Positions come without any user code: the text is split at a pattern and the same
pattern extracts the matches, so gaps and matches alternate and their lengths add
up to code-point offsets.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The base patterns, in their order.
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]{32,}"  # leftmost runs of 32 and more, the same as all runs without the shorter
# Parts that only count when complementary ones are near: identifiers, weak secrets, endpoints.  A name may
# follow a prefix ("DB_USER"), of which a part takes the "_" at most, and go on ("aws_secret_access_key").
IDENTIFIER = r"""(?i:(?:\b|_)(?:(?:user(?:name)?|login|account)(?:[_-]?(?:id|name))?|client_?id|access_?key_?id))["']?\x20*[:=]\x20*["']?[A-Za-z0-9@._-]{3,}|(?:\b|_)AKIA[A-Z0-9]{8,}"""
WEAK_SECRET = r"""(?i:(?:\b|_)(?:pwd|pass|password|passwd|passphrase|secret|token|api_?key|auth|signature|private_?key)(?:[_-](?:access|api|secret|private|auth|key|token|value|id)){0,3})["']?\x20*[:=]\x20*["']?[A-Za-z0-9+/_.=!@#$%^&*-]{4,}"""
ENDPOINT = r"""(?i:(?:\b|_)(?:https?|s3|ftp|ssh|jdbc:[a-z]+|postgres(?:ql)?|mysql|mongodb|redis|amqp))://[^\s"'<>]{3,}|(?i:(?:\b|_)(?:host|endpoint|server|url)(?:[_-]?(?:name|url))?)["']?\x20*[:=]\x20*["']?[A-Za-z0-9._:/-]{3,}"""

#: Code points between the parts of one credential, at most (the scope).
SCOPE = 200

_SPAN = "array<struct<start:int,rank:int,stop:int,kind:string>>"  # in the order of the spans


def spans_of(text: Column, pattern: str, kind: str, rank: int, keep_group: int | None = None, least: int = 0) -> Column:
    """Leftmost non-overlapping matches as (start, rank, stop, kind); with keep_group, only where that group is long enough.

    The expression is empty without further work where the pattern doesn't occur.
    """
    gaps = F.split(text, pattern, -1)
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    kept = F.regexp_extract_all(text, F.lit(pattern), F.lit(keep_group)) if keep_group else found
    sized = F.transform(F.arrays_zip(F.slice(gaps, F.lit(1), F.size(found)).alias("g"), found.alias("m"), kept.alias("k")), lambda x: F.struct(F.length(x["g"]).alias("g"), F.length(x["m"]).alias("m"), F.length(x["k"]).alias("k")))
    start = F.struct(F.lit(0).alias("at"), F.array().cast(_SPAN).alias("spans"))

    def step(acc: Column, x: Column) -> Column:
        begin = acc["at"] + x["g"]
        span = F.struct(begin.alias("start"), F.lit(rank).alias("rank"), (begin + x["m"]).alias("stop"), F.lit(kind).alias("kind"))
        return F.struct((begin + x["m"]).alias("at"), F.when(x["k"] >= least, F.concat(acc["spans"], F.array(span))).otherwise(acc["spans"]).alias("spans"))

    return F.when(text.rlike(pattern), F.aggregate(sized, start, step, lambda acc: acc["spans"])).otherwise(F.array().cast(_SPAN))


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["stop"].cast("string"))), ",")


def scan(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with ``__found`` (all spans by start, then kind) and ``__base`` (the base spans) added.

    Kinds: assign, access, hex are the base.  Then weak parts within SCOPE of a
    complementary one: ``linked_id`` (an identifier near a secret), ``linked_secret``
    (a secret near an identifier or an endpoint), ``linked_endpoint`` (an endpoint
    near both).  A weak part alone is never reported.  Null text counts as empty;
    empty tables and repeated rows need no special care.
    """
    body = F.coalesce(F.col(text), F.lit(""))
    df = docs.withColumn("__assign", spans_of(body, ASSIGN, "assign", 0, 2, 8)).withColumn("__access", spans_of(body, ACCESS, "access", 1, 0, 16)).withColumn("__hex", spans_of(body, HEX, "hex", 2))
    # A secret is needed for any link: without one the other patterns are not run.
    df = df.withColumn("__weak", spans_of(body, WEAK_SECRET, "linked_secret", 4))
    some = (F.size("__weak") > 0) | (F.size("__hex") > 0) | (F.size("__assign") > 0)
    none = F.array().cast(_SPAN)
    df = df.withColumn("__id", F.when(some, spans_of(body, IDENTIFIER, "linked_id", 3)).otherwise(none)).withColumn("__end", F.when(some, spans_of(body, ENDPOINT, "linked_endpoint", 5)).otherwise(none))
    secret = F.concat("__weak", "__assign", "__hex")

    def near(span: Column, others: Column) -> Column:
        # Interval join of two lists in one text; a part is no complement of one it overlaps.
        return F.exists(others, lambda o: (o["start"] <= span["stop"] + SCOPE) & (span["start"] <= o["stop"] + SCOPE) & ((o["stop"] <= span["start"]) | (span["stop"] <= o["start"])))

    linked_id = F.filter("__id", lambda s: near(s, secret))
    linked_secret = F.filter("__weak", lambda s: near(s, F.concat("__id", "__end")))
    linked_end = F.filter("__end", lambda s: near(s, secret) & near(s, F.col("__id")))
    df = df.withColumn("__base", F.array_sort(F.concat("__assign", "__access", "__hex"))).withColumn("__found", F.array_sort(F.concat("__assign", "__access", "__hex", linked_id, linked_secret, linked_end)))
    return df


def secret_digest(docs: DataFrame) -> DataFrame:
    """Per row: doc_id, counts of the base kinds, a digest of the base spans and all spans."""
    df = scan(docs.select("doc_id", "text"))
    return df.select(
        "doc_id", F.size("__assign").cast("long").alias("n_assign"), F.size("__access").cast("long").alias("n_access"), F.size("__hex").cast("long").alias("n_hex"),
        F.sha2(_joined(F.col("__base")), 256).alias("base_sha256"), _joined(F.col("__found")).alias("spans"),
    )


def redact(docs: DataFrame, mask: str = "[SECRET]") -> DataFrame:
    """The same columns, each found span replaced by ``mask`` (overlapping spans by one) and n_chars counted anew.

    Columns of any name pass through as they are.
    """
    df = scan(docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), "text"))
    body = F.coalesce(F.col("text"), F.lit(""))
    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("made"))

    def step(acc: Column, s: Column) -> Column:
        fresh = s["start"] >= acc["at"]
        kept = F.concat(acc["made"], body.substr(acc["at"] + 1, s["start"] - acc["at"]), F.lit(mask))
        return F.struct(F.greatest(acc["at"], s["stop"]).alias("at"), F.when(fresh, kept).otherwise(acc["made"]).alias("made"))

    clean = F.aggregate("__found", start, step, lambda acc: F.concat(acc["made"], body.substr(acc["at"] + 1, F.length(body))))
    text = F.when(F.size("__found") > 0, clean).otherwise(F.col("text"))
    fresh = {"text": F.col("text")}
    if "n_chars" in docs.columns:
        fresh["n_chars"] = F.when(F.size("__found") > 0, F.length("text").cast(dict(docs.dtypes)["n_chars"])).otherwise(F.col("row.n_chars"))
    df = df.withColumn("text", text)
    return df.select(*(fresh.get(c, F.col("row").getField(c)).alias(c) for c in docs.columns))
