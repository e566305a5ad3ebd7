"""Secret scans with multipart credential linking, in DataFrame functions only.

Base kinds (leftmost, not overlapping, per kind): ``assign``, ``access`` and ``hex``. Weak candidates are long
key-like runs (``weak_secret``) and addresses (``endpoint``). A weak candidate is reported only when a complementary
part lies within ``SCOPE`` characters: a secret needs an access identifier, an endpoint needs an access identifier
or an assignment. Linking is an interval join on (row, cell of the text): parts meet in the cells that their scopes
touch, then the true distance decides; it only asks whether a partner exists, so no pairs are made.

Positions: ``split`` gives what lies between matches and ``regexp_extract_all`` the matches, so offsets (code points)
are running sums of their lengths, taken in a window over one text's few matches. Texts without any match never
leave their scan task but for their id.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import free_name, row_key, staged

#: Fixed values of the scan: kind -> (pattern, group that must be long enough, its least length).
ASSIGN = r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
BASE = (("assign", ASSIGN, 2, 6), ("access", r"AKIA[A-Z0-9]+", 0, 20), ("hex", r"[0-9a-f]{24,}", 0, 24))
WEAK = (("weak_secret", r"[A-Za-z0-9+/]{32,}={0,2}", 0, 32), ("endpoint", r"https?://[A-Za-z0-9._~:/?#@!$&()*+,;=%-]+", 0, 10))
#: Cheap tests that a text must pass before the exact pattern runs.
HINT = {"assign": r"(?i:password|passwd|secret|token|api_?key)[\"']?\x20*[:=]", "access": r"AKIA[A-Z0-9]", "endpoint": r"https?://"}
SCOPE = 400
#: Complementary kinds of each weak kind.
PARTNERS = {"weak_secret": ("access",), "endpoint": ("access", "assign")}
ORDER = ("assign", "access", "hex", "weak_secret", "endpoint")


def _matches(kind: str, pattern: str, group: int, least: int) -> Column:
    """array<struct<pre, len, ok>>: characters before each match since the last one, its length, and if it counts."""
    text = F.col("text_")
    parts = F.split(text, pattern, -1)
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    judged = F.regexp_extract_all(text, F.lit(pattern), F.lit(group)) if group else found
    rows = F.transform(
        F.arrays_zip(F.slice(parts, F.lit(1), F.size(found)).alias("p"), found.alias("m"), judged.alias("g")),
        lambda z: F.struct(F.length(z["p"]).alias("pre"), F.length(z["m"]).alias("len"), (F.length(z["g"]) >= least).alias("ok")),
    )
    hint = text.rlike(HINT.get(kind, pattern))
    return F.when(hint, rows).otherwise(F.array().cast("array<struct<pre:int,len:int,ok:boolean>>"))


def _tagged(kind: str, number: int) -> Column:
    return F.transform(F.col(kind), lambda s, i: F.struct(F.lit(number).alias("kind"), i.alias("i"), s["pre"].alias("pre"), s["len"].alias("len"), s["ok"].alias("ok")))


def _count_of(number: int) -> Column:
    return F.size(F.filter("all", lambda x: x["kind"] == number)).cast("long").alias(f"n_{ORDER[number]}")


def matches(docs: DataFrame) -> DataFrame:
    """(doc_id, row_no, found): every row's matches of all kinds, as lengths, in one pass over the text."""
    text = docs.select("doc_id", F.coalesce(F.col("text"), F.lit("")).alias("text_"))
    kinds = [*BASE, *WEAK]
    each = text.select("doc_id", F.monotonically_increasing_id().alias("row_no"), *[_matches(*k).alias(k[0]) for k in kinds])
    return each.select("doc_id", "row_no", F.concat(*[_tagged(k[0], n) for n, k in enumerate(kinds)]).alias("found"))


def spans(found: DataFrame) -> DataFrame:
    """(row_no, kind int, start, end) of the matches that count."""
    rows = found.select("row_no", F.explode("found").alias("s")).select("row_no", "s.*")
    so_far = W.partitionBy("row_no", "kind").orderBy("i").rowsBetween(W.unboundedPreceding, 0)
    return rows.withColumn("end", F.sum(F.col("pre") + F.col("len")).over(so_far)).where("ok").select("row_no", "kind", (F.col("end") - F.col("len")).alias("start"), "end")


def linked(found: DataFrame, scope: int = SCOPE) -> DataFrame:
    """The weak spans that have a complementary part within ``scope`` characters and are no part of a base span."""
    number = {k: i for i, k in enumerate(ORDER)}
    cell = lambda c: F.floor(c / scope)
    base, weak = found.where(F.col("kind") < len(BASE)), found.where(F.col("kind") >= len(BASE))
    reach = F.sequence(cell(F.greatest(F.col("start") - scope, F.lit(0))), cell(F.col("end") + scope))
    ends = F.sequence(cell(F.col("p_start")), cell(F.col("p_end")))
    asks = weak.select("*", F.explode(reach).alias("cell"))
    parts = base.select("row_no", F.col("kind").alias("p_kind"), F.col("start").alias("p_start"), F.col("end").alias("p_end"))
    parts = parts.select("*", F.explode(ends).alias("cell"))
    fits = F.lit(False)
    for kind, partners in PARTNERS.items():
        fits = fits | ((F.col("kind") == number[kind]) & F.col("p_kind").isin([number[p] for p in partners]))
    near = (F.col("p_start") <= F.col("end") + scope) & (F.col("p_end") >= F.col("start") - scope)
    apart = (F.col("p_start") >= F.col("end")) | (F.col("p_end") <= F.col("start"))
    partner = asks.alias("w").join(
        parts.alias("p"), (F.col("w.row_no") == F.col("p.row_no")) & (F.col("w.cell") == F.col("p.cell")) & fits & near & apart, "left_semi"
    )
    kept = partner.select("row_no", "kind", "start", "end").distinct()
    # what lies inside a base span is that span already; one that only overlaps it goes on beyond and stays
    own = kept.alias("w").select("*", F.explode(F.sequence(cell(F.col("start")), cell(F.col("end")))).alias("cell"))
    covered = own.alias("w").join(
        parts.alias("p"), (F.col("w.row_no") == F.col("p.row_no")) & (F.col("w.cell") == F.col("p.cell")) & (F.col("p_start") <= F.col("w.start")) & (F.col("p_end") >= F.col("w.end")), "left_semi"
    ).select("row_no", "kind", "start", "end")
    return kept.join(covered, ["row_no", "kind", "start", "end"], "left_anti")


def _text_of(items: Column) -> Column:
    names = F.array(*[F.lit(k) for k in ORDER])
    return F.array_join(F.transform(items, lambda x: F.concat_ws(":", F.element_at(names, x["kind"] + 1), x["start"].cast("string"), x["end"].cast("string"))), ",")


def scan(docs: DataFrame, scope: int = SCOPE) -> DataFrame:
    """One row per document: doc_id, n_assign, n_access, n_hex, base_sha256, spans.

    Null texts are empty. Repeated ids are separate rows. An empty table gives an empty result.
    """
    numbered = staged(matches(docs))
    found = staged(spans(numbered))
    every = found.where(F.col("kind") < len(BASE)).unionByName(linked(found, scope))
    per_row = every.groupBy("row_no").agg(F.array_sort(F.collect_list(F.struct(F.col("start").cast("long").alias("start"), "kind", F.col("end").cast("long").alias("end")))).alias("all"))
    base = F.filter("all", lambda x: x["kind"] < len(BASE))
    told = per_row.select(
        "row_no", *[_count_of(i) for i in range(len(BASE))],
        _text_of(base).alias("base"), _text_of(F.col("all")).alias("spans"),
    )
    counts = [F.coalesce(f"n_{k}", F.lit(0).cast("long")).alias(f"n_{k}") for k in ORDER[: len(BASE)]]
    return numbered.select("doc_id", "row_no").join(told, "row_no", "left").select(
        "doc_id", *counts, F.sha2(F.coalesce("base", F.lit("")), 256).alias("base_sha256"), F.coalesce("spans", F.lit("")).alias("spans")
    )


def mask(docs: DataFrame, scope: int = SCOPE) -> DataFrame:
    """The documents with every reported span replaced by its kind in angle brackets; other columns stay.

    Overlapping spans are cut out together under the first one's kind. n_chars, where present, is counted anew for
    changed texts. Null texts stay null. Only rows with a span are joined, by (doc_id, SHA-256 of the text), which
    equal rows share; each stays a row. An empty table gives an empty result; column names may be any.
    """
    key, cuts_name = free_name(docs, "key"), free_name(docs, "cuts")
    mine = row_key(F.col("doc_id"), F.sha2(F.coalesce(F.col("text"), F.lit("")).cast("binary"), 256))
    numbered = staged(matches(docs.select(mine.alias("doc_id"), "text")))
    found = staged(spans(numbered))
    every = found.where(F.col("kind") < len(BASE)).unionByName(linked(found, scope))
    per_row = every.groupBy("row_no").agg(F.array_sort(F.collect_list(F.struct(F.col("start").cast("int").alias("start"), F.col("end").cast("int").alias("end"), "kind"))).alias(cuts_name))
    cuts = numbered.join(per_row, "row_no").select(F.col("doc_id").alias(key), cuts_name).dropDuplicates([key])
    names = F.array(*[F.lit(k) for k in ORDER])
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out"))
    walked = F.aggregate(
        cuts_name, start,
        lambda acc, c: F.when(c["start"] >= acc["at"], F.struct(c["end"].alias("at"), F.concat(acc["out"], F.array(F.substr(F.col("text"), acc["at"] + 1, c["start"] - acc["at"]), F.concat(F.lit("<"), F.element_at(names, c["kind"] + 1), F.lit(">")))).alias("out")))
        .otherwise(F.struct(F.greatest(acc["at"], c["end"]).alias("at"), acc["out"].alias("out"))),
        lambda acc: F.concat(F.array_join(acc["out"], ""), F.substr(F.col("text"), acc["at"] + 1, F.length("text"))),
    )
    joined = docs.select("*", mine.alias(key)).hint("merge").join(cuts, key, "left")
    changed = F.col(cuts_name).isNotNull()
    out = joined.select(*[F.when(changed, walked).otherwise(F.col("text")).alias("text") if c == "text" else F.col(f"`{c}`") for c in docs.columns], cuts_name)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(changed, F.length("text").cast("long")).otherwise(F.col("n_chars")).cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)
