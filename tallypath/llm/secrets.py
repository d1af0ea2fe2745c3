"""Secret scan with corpus-wide ownership frequency.

Base patterns mark assignments, access keys and hex strings. The method adds the kind
``owned``: every run of key characters that is long and mixed enough to be a credential is
a candidate; candidate hashes are counted over the whole corpus by distinct repositories and
distinct owners. A value seen under ``widely`` owners or more is a copied example; one that
stays with fewer is owner-specific and live-looking, and its spans are added. The same counts
tell each base span whether its value is an example, so that a caller can spare those.

Owners are people or organisations, repositories what they own; a value in one repository of each
of several owners is an example, one in many repositories of a single owner is still that owner's. Spans
carry both counts. A text is read in time proportional to its length.

Defined cases: a null or empty text has no spans; a null repository or owner counts as one
unnamed repository or owner; repeated rows count once in the frequencies (they are distinct
counts) and give repeated results; a null id is kept as it is; very long texts are scanned whole; an empty
table gives an empty result; other columns are ignored, also those called like the operator's own.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded, table, written

# The base kinds in their order, and their patterns.
KINDS = ("assign", "access", "hex")
ASSIGN = re.compile(
    r"""([Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
)
ACCESS = re.compile(r"AKIA[A-Z0-9]{14,}")
HEX = re.compile(r"[0-9a-f]{16,}")
CANDIDATE = re.compile(r"[A-Za-z0-9+/_-]{20,}={0,2}")

SPAN = "struct<kind:string,start:int,end:int,value:string,base:boolean>"


def base_spans(text: str) -> list[tuple[str, int, int, str]]:
    """(kind, start, end, value) of the base patterns by start, then kind; leftmost and non-overlapping within a kind."""
    found = [(m.start(), 0, m.end(), m[2]) for m in ASSIGN.finditer(text) if len(m[2]) >= 12]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end(), m[0]) for m in ACCESS.finditer(text)]
    found += [(m.start(), 2, m.end(), m[0]) for m in HEX.finditer(text)]
    return [(KINDS[k], a, b, v) for a, k, b, v in sorted(found)]


def untouched(base: list[tuple[str, int, int, str]], text: str) -> Iterator[re.Match]:
    """Candidates of ``text`` that overlap no base span: one sweep over both, each in order of start."""
    spans = sorted((a, b) for _, a, b, _ in base)
    at, reach = 0, -1
    for m in CANDIDATE.finditer(text):
        while at < len(spans) and spans[at][0] < m.end():
            reach = max(reach, spans[at][1])
            at += 1
        if reach <= m.start() and looks_random(m[0]):
            yield m


def looks_random(value: str) -> bool:
    """Mixed enough for a credential: digits among letters, and few repeats."""
    digits = sum(c.isdigit() for c in value)
    return 3 <= digits <= len(value) - 3 and len(set(value)) * 5 >= 2 * min(len(value), 25)


def digest(value: str) -> str:
    return hashlib.sha256(value.encode("utf-8", "surrogatepass")).hexdigest()[:32]


def scan(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` with ``spans``: base spans and candidates (``base`` false), values as hashes only."""

    @F.pandas_udf(f"array<{SPAN}>")
    def spans(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for texts in batches:
            out = []
            for t in texts:
                got = []
                if t:
                    base = base_spans(t)
                    got = [{"kind": k, "start": a, "end": b, "value": digest(v), "base": True} for k, a, b, v in base]
                    for m in untouched(base, t):
                        got.append({"kind": "owned", "start": m.start(), "end": m.end(), "value": digest(m[0]), "base": False})
                out.append(got)
            yield pd.Series(out)

    return docs.withColumn("spans", spans(F.col(text_col)))


def _named(docs: DataFrame, **columns: str) -> DataFrame:
    """The given columns of ``docs`` under names of the operator's own."""
    return docs.select(*[F.col(c).alias(k) for k, c in columns.items()])


def ownership(scanned: DataFrame) -> DataFrame:
    """value -> distinct repositories and owners over the whole corpus, of ``scanned`` (repo, owner, spans); equal rows meet before they are dealt out."""
    named = lambda c: F.coalesce(F.col(c).cast("string"), F.lit("")).alias(c)
    each = scanned.where(F.size("spans") > 0).select(named("repo"), named("owner"), F.explode("spans.value").alias("value"))
    by = each.groupBy("value", "owner", "repo").agg(F.count("*").alias("n"))
    return by.groupBy("value").agg(F.count_distinct("owner", "repo").alias("repos"), F.count_distinct("owner").alias("owners"), F.sum("n").alias("copies"))


FOUND = "array<struct<start:int,end:int,kind:string,base:boolean,value:string,owners:bigint,repos:bigint,live:boolean>>"


def find_secrets(docs: DataFrame, id_col: str = "doc_id", repo_col: str = "source", owner_col: str = "source", widely: int = 3) -> DataFrame:
    """A row per row of ``docs``: ``id_col``, ``text_key`` (hash of the text) and ``spans`` with ``owners``, ``repos`` and ``live`` (seen under fewer than ``widely`` owners).

    Candidates of widely copied values are left out; base spans always stay.
    """
    own = _named(bounded(docs), id=id_col, repo=repo_col, owner=owner_col, text="text")
    scanned = written(scan(own).withColumn("text_key", F.xxhash64("text")).drop("text").withColumn("row", F.monotonically_increasing_id()), "secrets")
    seen = ownership(scanned)
    each = scanned.where(F.size("spans") > 0).select("row", F.explode("spans").alias("s")).withColumn("value", F.col("s.value"))
    judged = each.join(seen, "value").where(F.col("s.base") | (F.col("owners") < widely))
    span = F.struct(F.col("s.start").alias("start"), F.col("s.end").alias("end"), F.col("s.kind").alias("kind"), F.col("s.base").alias("base"), "value", "owners", "repos", (F.col("owners") < widely).alias("live"))
    back = judged.groupBy("row").agg(F.collect_list(span).alias("found"))
    none = F.array().cast(FOUND)
    return scanned.select("row", "id", "text_key").join(back, "row", "left").select(F.col("id").alias(id_col), "text_key", F.coalesce("found", none).alias("spans"))


def _order(spans: str):
    """Spans by start, then kind as listed (added ones last)."""
    rank = F.create_map(*[x for i, k in enumerate((*KINDS, "owned")) for x in (F.lit(k), F.lit(i))])
    return F.array_sort(F.transform(F.col(spans), lambda s: F.struct(s["start"].alias("start"), rank[s["kind"]].alias("k"), s["end"].alias("end"), s["kind"].alias("kind"), s["base"].alias("base"))))


def _joined(spans):
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def digest_columns(found: DataFrame) -> DataFrame:
    """The contract's columns from the operator's spans."""
    of = lambda kind: F.size(F.filter("o", lambda s: s["base"] & (s["kind"] == kind))).cast("long")
    return found.withColumn("o", _order("spans")).select(
        "doc_id", *(of(k).alias(f"n_{k}") for k in KINDS), F.sha2(_joined(F.filter("o", lambda s: s["base"])), 256).alias("base_sha256"), _joined(F.col("o")).alias("spans")
    )


def redact(docs: DataFrame, found: DataFrame, id_col: str = "doc_id", mask: str = "[secret]") -> DataFrame:
    """``docs`` with live-looking spans replaced in ``text`` and ``n_chars`` set anew; every row stays."""
    live = found.select(F.col(id_col).alias("__id"), F.col("text_key").alias("__key"), F.filter("spans", lambda s: s["live"]).alias("__s")).where(F.size("__s") > 0).dropDuplicates(["__id", "__key"])

    @F.pandas_udf("string")
    def masked(texts: pd.Series, spans: pd.Series) -> pd.Series:
        out = []
        for t, found in zip(texts, spans):
            if t and found is not None and len(found):
                parts, at = [], 0
                for s in sorted(found, key=lambda s: (s["start"], -s["end"])):
                    if s["start"] >= at:
                        parts += [t[at : s["start"]], mask]
                    at = max(at, s["end"])
                t = "".join([*parts, t[at:]])
            out.append(t)
        return pd.Series(out, dtype=object)

    cols = docs.columns
    text = F.when(F.col("__s").isNull(), F.col("text")).otherwise(masked("text", "__s"))
    new = docs.join(live, docs[id_col].eqNullSafe(F.col("__id")) & (F.xxhash64(docs["text"]) == F.col("__key")), "left").withColumn("text", text)
    if "n_chars" in cols:
        new = new.withColumn("n_chars", F.when(F.col("__s").isNull(), F.col("n_chars")).otherwise(F.length("text").cast(docs.schema["n_chars"].dataType)))
    return new.select(*cols)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest_columns(find_secrets(table(spark, sf_dir, "documents")))


def value_entropy(value: str) -> float:
    """Shannon entropy of the characters of ``value`` in bits: for callers that set a bound of their own."""
    _, n = np.unique(list(value), return_counts=True)
    p = n / n.sum()
    return float(-(p * np.log2(p)).sum()) if len(n) else 0.0
