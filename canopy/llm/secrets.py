"""Secret scans with an incremental ledger of content-addressed blobs.

Every version of every path is addressed by the SHA-256 of its text. The
ledger holds, for each blob, the rule versions it was scanned with and what
they found. A scan reads a text only for blobs with a rule version the ledger
lacks, once per blob; findings are then joined back to all paths.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from hashlib import sha256

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.arrow import arrow_map
from canopy.storage import fresh_path

# fixed values: the base patterns, the group that is measured and its least length, in the order of kinds
RULES = {
    "assign": (r"""(?ai)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    "access": (r"AKIA[A-Z0-9]+", 0, 20),
    "hex": (r"[0-9a-f]+", 0, 24),
    "pem": (r"-----BEGIN [A-Z ]*PRIVATE KEY-----[A-Za-z0-9+/=\s]*-----END [A-Z ]*PRIVATE KEY-----", 0, 0),
    "jwt": (r"eyJ[A-Za-z0-9_-]+\.eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+", 0, 30),
    "ghtoken": (r"gh[pousr]_[A-Za-z0-9]+", 0, 40),
}
BASE = ("assign", "access", "hex")
MASK = "[SECRET]"
FOUND = "array<struct<start:int,kind:int,stop:int>>"


def version_of(kind: str, rule: tuple) -> str:
    return f"{kind}:{sha256(repr(rule).encode()).hexdigest()[:12]}"


#: Same matches as the plain pattern and its least length; that one stops at every digit of every word.
FAST = {"hex": re.compile(r"[0-9a-f]{24,}")}
KEYWORDS = ("passw", "secret", "token", "apikey", "api_key")


def scan(text: str, kinds: list[str], rules: dict = RULES) -> list[tuple[int, int, int]]:
    """(start, number of the kind, end) of the leftmost non-overlapping matches of each kind, sorted."""
    out, lowered = [], text.lower()
    for number, kind in enumerate(rules):
        if kind not in kinds:
            continue
        pattern, group, least = rules[kind]
        if rules[kind] == RULES.get(kind) and kind == "assign" and not any(map(lowered.__contains__, KEYWORDS)):
            continue
        for m in (FAST[kind] if kind in FAST and rules[kind] == RULES[kind] else re.compile(pattern)).finditer(text):
            if len(m[group]) >= least:
                out.append((m.start(), number, m.end()))
    return sorted(out)


def scan_versions(docs: DataFrame, ledger: str | None = None, rules: dict = RULES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id, blob, found)``: what all rules find in each version's text.

    ``ledger`` is the folder of the ledger; pairs of blob and rule version it
    holds are not scanned again, new ones are appended to it. Null texts count
    as empty; a null id or a repeated row is a version like any other (rows of
    equal id and text are scanned each, their findings are one). Whole texts
    are scanned, however long; columns of ``docs`` named like those here do
    not matter. Empty input appends nothing and gives no row. A scan that its
    caller repeats may append its rows again, which reading merges.
    """
    spark = docs.sparkSession
    ledger = ledger or fresh_path(spark, "ledger")
    versions = {version_of(k, r): k for k, r in rules.items()}
    wanted = F.array(*map(F.lit, versions))
    text = F.coalesce(F.col(text_col), F.lit(""))
    paths = docs.select(F.col(id_col).cast("long").alias(id_col), F.sha2(text, 256).alias("blob"))
    seen = read_ledger(spark, ledger)
    need = paths.groupBy("blob").agg(F.min(id_col).alias("at")).withColumn("versions", wanted)
    if seen is not None:
        done = seen.groupBy("blob").agg(F.flatten(F.collect_list("versions")).alias("done"))
        need = need.join(done, "blob", "left").select("blob", "at", F.array_except(wanted, F.coalesce("done", F.array().cast("array<string>"))).alias("versions"))
    need = need.where(F.size("versions") > 0)

    def make():
        def step(blobs: list, texts: list, todo: list) -> Iterator[tuple]:
            for blob, text, kinds in zip(blobs, texts, todo):
                yield blob, kinds, [{"start": s, "kind": k, "stop": e} for s, k, e in scan(text, [versions[v] for v in kinds], rules)]

        return step

    # one path of each blob carries its text; an id may be null or name several texts, so both are compared
    texts = docs.select(F.col(id_col).cast("long").alias("at"), text.alias("text"), F.sha2(text, 256).alias("blob"))
    same = texts["at"].eqNullSafe(need["at"]) & (texts["blob"] == need["blob"])
    fresh = texts.join(need, same).select(need["blob"], "text", "versions")
    arrow_map(fresh, make, f"blob string, versions array<string>, found {FOUND}").write.mode("append").parquet(ledger)
    known = read_ledger(spark, ledger).where(F.size("found") > 0).where(F.arrays_overlap("versions", wanted))
    per_blob = known.groupBy("blob").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("found")))).alias("found"))
    return paths.join(per_blob, "blob", "left").select(id_col, "blob", F.coalesce("found", F.array().cast(FOUND)).alias("found"))


def read_ledger(spark, path: str) -> DataFrame | None:
    """The ledger's rows, None before the first scan."""
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    if not target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(target):
        return None
    return spark.read.schema(f"blob string, versions array<string>, found {FOUND}").parquet(path)


def joined(found: str, kinds: tuple[str, ...] | list[str]) -> F.Column:
    """``kind:start:end`` of the spans of these kinds (the first ones of the rules), comma-joined."""
    names = F.array(*map(F.lit, RULES))
    mine = F.filter(found, lambda x: x["kind"] < len(kinds))
    return F.array_join(F.transform(mine, lambda x: F.concat_ws(":", F.element_at(names, x["kind"] + 1), x["start"].cast("string"), x["stop"].cast("string"))), ",")


def digest(scanned: DataFrame) -> DataFrame:
    """The columns of a scan report: counts and hash of the base kinds, and all spans."""

    def of_kind(number: int):  # a lambda with a default would be given the element's place
        return lambda x: x["kind"] == number

    counts = [F.size(F.filter("found", of_kind(k))).cast("long").alias(f"n_{kind}") for k, kind in enumerate(BASE)]
    return scanned.select("doc_id", *counts, F.sha2(joined("found", BASE), 256).alias("base_sha256"), joined("found", list(RULES)).alias("spans"))


def mask(text: str, spans: list[tuple[int, int]]) -> str:
    """The text with overlapping spans merged and replaced by a mark."""
    out, at, merged = [], 0, []
    for start, stop in sorted(spans):
        if merged and start <= merged[-1][1]:
            merged[-1][1] = max(merged[-1][1], stop)
        else:
            merged.append([start, stop])
    for start, stop in merged:
        out += [text[at:start], MASK]
        at = stop
    return "".join([*out, text[at:]])


def redact(docs: DataFrame, ledger: str | None = None) -> DataFrame:
    """``docs`` with every span replaced by a mark and ``n_chars`` counted anew.

    Texts without a finding, and null ones, stay as they are.
    """
    blobs = scan_versions(docs, ledger).where(F.size("found") > 0).groupBy("blob").agg(F.first("found").alias("found"))
    marked = docs.withColumn("blob", F.sha2(F.coalesce("text", F.lit("")), 256)).join(blobs, "blob", "left")

    @F.pandas_udf("string")
    def masked(text: pd.Series, found: pd.Series) -> pd.Series:
        return pd.Series([mask(t, [(x["start"], x["stop"]) for x in f]) if f is not None and len(f) else t for t, f in zip(text, found)])

    new = marked.withColumn("text", masked("text", "found")).withColumn("n_chars", F.when(F.col("found").isNotNull(), F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return new.select(docs.columns)
