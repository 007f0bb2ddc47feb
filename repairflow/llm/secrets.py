"""Secret scans over a content-addressed blob ledger, in DataFrame functions only.

Every version of a text is a blob named by its SHA-256.  The ledger records which
rules, by name and version, have been run on which blob and what they found; a
scan joins the blobs at hand with it, runs on each blob only the rules that have
no record there, appends the new records, and joins findings back to every path
whose text is that blob.  A text that occurs in a million files is scanned once.

Spans are code points, end exclusive.  Defined results: a null text is the empty
text; equal texts get equal findings; paths may be null or repeat.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Rule:
    """Leftmost non-overlapping matches of ``pattern`` whose group has ``least`` characters.

    ``needs`` are literals in lower case of which a text must hold one, in any case,
    for the rule to match; a rule without them is tried by its pattern.
    """

    kind: str
    pattern: str
    least: int
    group: int = 0
    needs: tuple[str, ...] = ()
    version: int = 1

    @property
    def name(self) -> str:
        return f"{self.kind}@{self.version}"


# The three base rules.
BASE_RULES = (
    Rule("assign", r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 8, 2, ("password", "passwd", "secret", "token", "apikey", "api_key")),
    Rule("access", r"AKIA[A-Z0-9]+", 16, 0, ("akia",)),
    Rule("hex", r"[0-9a-f]{32,}", 32),
)
EXTRA_RULES = (
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", 32, 0, ("eyj",)),
    Rule("pem", r"-----BEGIN (?:[A-Z]+ )*PRIVATE KEY-----[A-Za-z0-9+/=\s]*-----END (?:[A-Z]+ )*PRIVATE KEY-----", 60, 0, ("-----begin",)),
)
RULES = BASE_RULES + EXTRA_RULES

_SPAN = "struct<kind:string,start:bigint,stop:bigint,rule:string>"
_LEDGER = f"blob string, rules array<string>, spans array<{_SPAN}>"


def rule_spans(text, rule: Rule):
    """Spans of one rule as an array column.

    Splitting at the pattern gives what lies between its matches, so offsets are
    running sums of the lengths of pieces and matches.
    """
    pattern = F.lit(rule.pattern)
    match = F.regexp_extract_all(text, pattern, F.lit(0))
    value = F.regexp_extract_all(text, pattern, F.lit(rule.group)) if rule.group else match
    parts = F.arrays_zip(F.split(text, rule.pattern, -1).alias("gap"), match.alias("hit"), value.alias("val"))
    empty = F.expr(f"cast(array() as array<{_SPAN}>)")

    def step(acc, x):
        begin = acc["at"] + F.length(x["gap"])
        end = begin + F.length(x["hit"])
        span = F.struct(F.lit(rule.kind).alias("kind"), begin.alias("start"), end.alias("stop"), F.lit(rule.name).alias("rule"))
        return F.struct(end.alias("at"), F.when(F.length(x["val"]) >= rule.least, F.concat(acc["out"], F.array(span))).otherwise(acc["out"]).alias("out"))

    found = F.aggregate(F.filter(parts, lambda x: x["hit"].isNotNull()), F.struct(F.lit(0).cast("long").alias("at"), empty.alias("out")), step, lambda acc: acc["out"])
    return F.when(text.rlike(rule.pattern), found).otherwise(empty)


def may_match(text, folded, rules: tuple[Rule, ...]):
    """Whether any rule could match, by literals where it has them."""
    out = F.lit(False)
    for rule in rules:
        for literal in rule.needs:
            out = out | folded.contains(literal)
        if not rule.needs:
            out = out | text.rlike(rule.pattern)
    return out


def scan(versions: DataFrame, ledger: DataFrame | None = None, text_col: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Ledger rows (blob, rules, spans) of what the ledger lacks for these versions."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    # Texts that no rule can match need not travel to be recorded as scanned.
    named = versions.select(F.sha2(text, 256).alias("blob"), F.when(may_match(text, F.lower(text), rules), text).alias("text"))
    blobs = named.groupBy("blob").agg(F.first("text", ignorenulls=True).alias("text")).withColumn("text", F.coalesce("text", F.lit("")))
    if ledger is None:
        blobs = blobs.withColumn("known", F.expr("cast(array() as array<string>)"))
    else:
        known = ledger.groupBy("blob").agg(F.array_distinct(F.flatten(F.collect_list("rules"))).alias("known"))
        blobs = blobs.join(known, "blob", "left").withColumn("known", F.coalesce("known", F.expr("cast(array() as array<string>)")))
    names = F.array(*[F.lit(r.name) for r in rules])
    todo = blobs.withColumn("rules", F.array_except(names, "known")).filter(F.size("rules") > 0)
    none = F.expr(f"cast(array() as array<{_SPAN}>)")
    spans = F.concat(*[F.when(F.array_contains("rules", r.name), rule_spans(F.col("text"), r)).otherwise(none) for r in rules])
    return todo.select("blob", "rules", spans.alias("spans"))


def update_ledger(versions: DataFrame, path: str, text_col: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Append what is new to the ledger at ``path`` and return the whole of it."""
    spark = versions.sparkSession
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    there = folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(folder)
    old = spark.read.schema(_LEDGER).parquet(path) if there else None
    scan(versions, old, text_col, rules).write.mode("append").parquet(path)
    return spark.read.schema(_LEDGER).parquet(path)


def findings(versions: DataFrame, ledger: DataFrame, text_col: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Every version's columns but the text, with its blob and its spans by start, then rule order."""
    order = F.create_map(*[x for i, r in enumerate(rules) for x in (F.lit(r.name), F.lit(i))])
    current = F.filter(F.flatten(F.collect_list("spans")), lambda s: s["rule"].isin([r.name for r in rules]))
    # Re-run records may hold a span twice.
    sortable = F.transform(F.array_distinct(current), lambda s: F.struct(s["start"].alias("start"), order[s["rule"]].alias("n"), s["kind"].alias("kind"), s["stop"].alias("stop")))
    by_blob = ledger.filter(F.size("spans") > 0).groupBy("blob").agg(F.array_sort(sortable).alias("_spans"))
    keep = [F.col(f"`{c}`") for c in versions.columns if c != text_col]
    paths = versions.select(*keep, F.sha2(F.coalesce(F.col(text_col), F.lit("")), 256).alias("_blob"))
    return paths.join(by_blob, paths["_blob"] == by_blob["blob"], "left").drop("blob")


def digest(found: DataFrame, base: tuple[Rule, ...] = BASE_RULES) -> DataFrame:
    """The contract's digest columns of findings."""
    spans = F.coalesce("_spans", F.expr("cast(array() as array<struct<start:bigint,n:int,kind:string,stop:bigint>>)"))
    text = lambda xs: F.array_join(F.transform(xs, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["stop"].cast("string"))), ",")
    kinds = [r.kind for r in base]
    count = lambda kind: F.size(F.filter(spans, lambda s: s["kind"] == kind)).cast("long")
    counts = [count(k).alias(f"n_{k}") for k in kinds]
    base_spans = F.filter(spans, lambda s: s["kind"].isin(kinds))
    return found.select("doc_id", *counts, F.sha2(text(base_spans), 256).alias("base_sha256"), text(spans).alias("spans"))
