"""Secret scan with corpus-wide ownership frequency, in DataFrame functions only.

Patterns find candidates in every whole text; a candidate's value is hashed at once and only hashes
travel. The corpus then says how many repositories (documents) and owners (sources) each hash occurs
with: a value that many owners share is a copied example, one that stays with its owner looks live.
Base candidates are always reported; candidates of the further, looser kinds add a span only where
ownership makes them look live.

Spans are code points, end exclusive. They come from the lengths of the matches and of what lies
between them, so each kind costs one pass over a text without candidates.

Defined results: null text is empty text; a null source is an owner of its own; every input row gives
one output row, repeated ones too; no candidates give counts of 0 and the digest of the empty
string; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from motifloom.llm.common import durable


@dataclass(frozen=True)
class Kind:
    name: str
    pattern: str
    #: Group whose text is the secret and which has to be min_length long.
    group: int = 0
    min_length: int = 0
    base: bool = False


# fixed values: the base kinds in their order, then the looser kinds
KINDS = (
    Kind("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 12, True),
    Kind("access", r"AKIA[A-Z0-9]+", 0, 18, True),
    Kind("hex", r"[0-9a-f]{16,}", 0, 16, True),
    Kind("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
    Kind("vendor", r"(?:ghp|gho|glpat|xoxb|xoxp|sk_live|rk_live)[_-][A-Za-z0-9_-]{16,}"),
    Kind("pem", r"-----BEGIN [A-Z ]*PRIVATE KEY-----[A-Za-z0-9+/=\s]*"),
    Kind("url", r"://[^\s:/@]*:([^\s:/@]{6,})@", 1, 6),
)

#: A value with so many owners is a copied example, in however many documents it stands.
OWNERS = 3
_BLOCK = 256


def _places(lengths: Column) -> Column:
    """array<struct<gap, long>> -> array<struct<start, stop>>, by running sums in blocks."""
    empty = "array<struct<start:bigint,stop:bigint>>"

    def step(acc, x):
        start = acc["at"] + x["gap"]
        return F.struct((start + x["long"]).alias("at"), F.concat(acc["out"], F.array(F.struct(start.alias("start"), (start + x["long"]).alias("stop")))).alias("out"))

    def block(acc, part):
        inner = F.aggregate(part, F.struct(acc["at"].alias("at"), F.array().cast(empty).alias("out")), step)
        return F.get(F.transform(F.array(inner), lambda i: F.struct(i["at"].alias("at"), F.concat(acc["out"], F.array(i["out"])).alias("out"))), F.lit(0))

    parts = F.transform(F.sequence(F.lit(0), F.floor((F.size(lengths) - 1) / _BLOCK).cast("int")), lambda b: F.slice(lengths, b * _BLOCK + 1, F.lit(_BLOCK)))
    start = F.struct(F.lit(0).cast("bigint").alias("at"), F.array().cast(f"array<{empty}>").alias("out"))
    return F.flatten(F.aggregate(parts, start, block)["out"])


def _spans(text: Column, kind: Kind, order: int) -> Column:
    """array<struct<start, rank, kind, stop, hash, base>> of one kind in a text."""
    whole = F.regexp_extract_all(text, F.lit(kind.pattern), F.lit(0))
    value = F.regexp_extract_all(text, F.lit(kind.pattern), F.lit(kind.group))
    between = F.split(text, kind.pattern, -1)
    lengths = F.zip_with(F.slice(between, F.lit(1), F.size(whole)), whole, lambda g, m: F.struct(F.length(g).cast("bigint").alias("gap"), F.length(m).cast("bigint").alias("long")))
    joined = F.zip_with(_places(lengths), value, lambda p, v: F.struct(p["start"].alias("start"), F.lit(order).alias("rank"), F.lit(kind.name).alias("kind"), p["stop"].alias("stop"), F.length(v).alias("n"), F.sha2(v, 256).alias("hash"), F.lit(kind.base).alias("base")))
    good = F.transform(F.filter(joined, lambda s: s["n"] >= kind.min_length), lambda s: F.struct(*[s[c].alias(c) for c in ("start", "rank", "kind", "stop", "hash", "base")]))
    none = F.array().cast("array<struct<start:bigint,rank:int,kind:string,stop:bigint,hash:string,base:boolean>>")
    return F.when(text.rlike(kind.pattern), good).otherwise(none)


def candidates(docs: DataFrame, kinds: tuple[Kind, ...] = KINDS) -> DataFrame:
    """row (unique), doc_id, owner, spans for every row of docs; durable, since row numbers are."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(F.col("doc_id"), F.col("source").cast("string").alias("owner"), text.alias("text"))
    found = rows.select("doc_id", "owner", F.concat(*[_spans(F.col("text"), k, i) for i, k in enumerate(kinds)]).alias("spans"))
    return durable(found.withColumn("row", F.monotonically_increasing_id()))


def ownership(found: DataFrame, owners: int = OWNERS) -> DataFrame:
    """hash, n_repositories, n_owners, live: how widely each candidate value is spread.

    Counts are built from distinct (hash, document) and (hash, owner) pairs, which are pre-aggregated
    where they arise, so a value that everyone copies makes no hot task.
    """
    seen = found.select("doc_id", "owner", F.explode("spans.hash").alias("hash"))
    repos = seen.groupBy("hash", "doc_id").agg(F.lit(1).alias("one")).groupBy("hash").agg(F.count(F.lit(1)).alias("n_repositories"))
    owned = seen.groupBy("hash", "owner").agg(F.lit(1).alias("one")).groupBy("hash").agg(F.count(F.lit(1)).alias("n_owners"))
    spread = repos.join(owned, "hash")
    return spread.withColumn("live", F.col("n_owners") < owners)


def _text_of(spans: Column) -> Column:
    ordered = F.array_sort(F.transform(spans, lambda s: F.struct(s["start"], s["rank"], s["stop"], s["kind"])))
    return F.concat_ws(",", F.transform(ordered, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["stop"].cast("string"))))


def _count(kind: Kind) -> Column:
    return F.size(F.filter("spans", lambda s: s["kind"] == F.lit(kind.name)))


def scan(docs: DataFrame, kinds: tuple[Kind, ...] = KINDS, owners: int = OWNERS) -> DataFrame:
    """One row per row of docs: doc_id, n_<base kind>…, base_sha256, spans, n_live, n_copied."""
    found = candidates(docs, kinds)
    verdicts = ownership(found, owners).select("hash", "live")
    each = found.where(F.size("spans") > 0).select("row", F.explode("spans").alias("span")).select("row", "span", F.col("span.hash").alias("hash"))
    judged = each.join(verdicts, "hash").groupBy("row").agg(
        F.collect_list(F.when(F.col("span.base") | F.col("live"), F.col("span"))).alias("reported"),
        F.sum(F.col("live").cast("long")).alias("n_live"),
        F.sum((~F.col("live")).cast("long")).alias("n_copied"),
    )
    out = found.join(judged, "row", "left")
    base = F.filter("spans", lambda s: s["base"])
    counts = [_count(k).cast("long").alias(f"n_{k.name}") for k in kinds if k.base]
    return out.select(
        "doc_id",
        *counts,
        F.sha2(_text_of(base), 256).alias("base_sha256"),
        F.coalesce(_text_of(F.col("reported")), F.lit("")).alias("spans"),
        F.coalesce("n_live", F.lit(0)).alias("n_live"),
        F.coalesce("n_copied", F.lit(0)).alias("n_copied"),
    )
