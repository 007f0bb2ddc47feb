"""Repairs as rows: the pool, its ids, and binding rows to the repairs that match them."""

from __future__ import annotations

from collections.abc import Iterable, Mapping
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.predicates import comparable, literal
from ..model import CLAUSE_TYPE, POOL_SCHEMA, Clause, Repair

_NONE = "\x05"


def clause_struct(attr: str, op: str, lo: Column | None = None, hi: Column | None = None, lo_incl: bool = True, hi_incl: bool = True, vals: Column | None = None) -> Column:
    null = F.lit(None).cast("string")
    return F.struct(
        F.lit(attr).alias("attr"),
        F.lit(op).alias("op"),
        (null if lo is None else lo.cast("string")).alias("lo"),
        (null if hi is None else hi.cast("string")).alias("hi"),
        F.lit(lo_incl).alias("lo_incl"),
        F.lit(hi_incl).alias("hi_incl"),
        (F.lit(None).cast("array<string>") if vals is None else vals).alias("vals"),
    )


def repair_id(pred: Column, target: Column, value: Column) -> Column:
    """Sixty bits of an MD5 of what the repair does; tools and settings do not count."""
    show = lambda c: F.coalesce(c, F.lit(_NONE))
    clause = lambda c: F.concat_ws("\x01", c["attr"], c["op"], show(c["lo"]), show(c["hi"]), c["lo_incl"].cast("string"), c["hi_incl"].cast("string"), F.coalesce(F.array_join(c["vals"], "\x02"), F.lit("")))
    body = F.concat_ws("\x04", F.array_join(F.transform(pred, clause), "\x03"), target, show(value))
    return F.conv(F.substring(F.md5(body), 1, 15), 16, 10).cast("long")


def repair_rows(df: DataFrame, clauses: list[Column], sig: str, target: str, value: Column, op: str, params: Mapping[str, object] | None = None) -> DataFrame:
    """Pool rows, one for each row of ``df``; clauses and value may use its columns.

    ``sig`` lists attr:op of the clauses.  A repair is its own unit.
    """
    params = {k: str(v) for k, v in (params or {}).items()}
    texts = F.create_map(*[F.lit(x) for kv in params.items() for x in kv]) if params else F.create_map().cast("map<string,string>")
    nums = {k: float(v) for k, v in params.items() if v.replace(".", "", 1).replace("-", "", 1).isdigit()}
    numbers = F.create_map(*[F.lit(x) for kv in nums.items() for x in kv]) if nums else F.create_map().cast("map<string,double>")
    rows = df.select(F.array(*clauses).cast(f"array<{CLAUSE_TYPE}>").alias("pred"), F.lit(sig).alias("pred_sig"), F.lit(target).alias("target"), value.cast("string").alias("value"))
    rows = rows.withColumn("repair_id", repair_id(F.col("pred"), F.col("target"), F.col("value")))
    return rows.select(
        "repair_id", F.col("repair_id").alias("unit"), F.lit(0).alias("pos"), "pred", "pred_sig", "target", "value", F.col("value").isNull().alias("value_is_null"), F.lit(op).alias("op"), texts.alias("params"), numbers.alias("num_params")
    )


def equality_repairs(df: DataFrame, keys: Mapping[str, Column], target: str, value: Column, op: str, params: Mapping[str, object] | None = None) -> DataFrame:
    """Repairs whose predicate is a conjunction of equalities."""
    attrs = sorted(keys)
    return repair_rows(df, [clause_struct(a, "eq", keys[a]) for a in attrs], ",".join(f"{a}:eq" for a in attrs), target, value, op, params)


def pool_of(spark: SparkSession, repairs: Iterable[Repair]) -> DataFrame:
    """The pool rows of repair objects; those of one bundle share a unit."""
    text = lambda v: None if v is None else str(v)
    rows, units = [], {}
    for i, r in enumerate(repairs):
        pred = [(c.attr, c.op, text(c.lo), text(c.hi), c.lo_incl, c.hi_incl, [text(v) for v in c.vals] if c.vals else None) for c in r.pred]
        rows.append((i, r.bundle, pred, r.signature, r.target, text(r.value), r.op, dict(r.params)))
        units.setdefault(r.bundle, i)
    df = spark.createDataFrame(rows, f"pos int, bundle string, pred array<{CLAUSE_TYPE}>, pred_sig string, target string, value string, op string, params map<string,string>")
    df = df.withColumn("repair_id", repair_id(F.col("pred"), F.col("target"), F.col("value")))
    unit = F.when(F.col("bundle").isNull(), F.col("repair_id")).otherwise(F.conv(F.substring(F.md5("bundle"), 1, 15), 16, 10).cast("long"))
    return df.select("repair_id", unit.alias("unit"), "pos", "pred", "pred_sig", "target", "value", F.col("value").isNull().alias("value_is_null"), "op", "params", F.create_map().cast("map<string,double>").alias("num_params"))


def empty_pool(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([], POOL_SCHEMA)


def canonicalize(pool: DataFrame) -> DataFrame:
    """One row for each distinct edit of a unit, however many tools or settings made it."""
    first = [F.first(c).alias(c) for c in ("pred", "pred_sig", "target", "value", "value_is_null", "op", "params", "num_params")]
    return pool.groupBy("unit", "repair_id").agg(F.min("pos").alias("pos"), *first).select(*pool.columns)


def bundle(pool: DataFrame) -> DataFrame:
    """All repairs of one tool and setting as one unit, a meta assignment."""
    label = F.concat_ws("|", "op", F.to_json(F.array_sort(F.map_entries("params"))))
    return pool.withColumn("unit", F.conv(F.substring(F.md5(label), 1, 15), 16, 10).cast("long"))


def _matches(i: int, attr: str, op: str, kind: str) -> Column:
    """Condition of the i-th clause: columns ``_r_*`` of the rows, ``_*i`` of the pool."""
    col = F.col(f"_r_{attr}")
    lo, hi = F.col(f"_lo{i}"), F.col(f"_hi{i}")
    x, a, b = comparable(col, kind), literal(lo, kind), literal(hi, kind)
    if op == "eq":
        return x == a
    if op == "in":
        return F.array_contains(F.transform(f"_vals{i}", lambda v: literal(v, kind)), x)
    if op == "prefix":
        return col.cast("string").startswith(lo)
    if op == "is_null":
        return col.isNull()
    if op == "not_null":
        return col.isNotNull()
    if op == "between":
        low = F.when(F.col(f"_li{i}"), x >= a).otherwise(x > a) | lo.isNull()
        return low & (F.when(F.col(f"_hx{i}"), x <= b).otherwise(x < b) | hi.isNull())
    return {"lt": x < a, "le": x <= a, "gt": x > a, "ge": x >= a}[op]


def bind(pool: DataFrame, rows: DataFrame, key: tuple[str, ...], carry: bool = False) -> DataFrame:
    """(unit, repair_id, pos, *key, target, new, [b]): the cells repairs would change.

    Repairs are split by the attributes and operators of their predicates: those
    with equalities meet the rows in a hash or merge join on these attributes, the
    rest in a join on their conditions.  Repairs that change nothing are left out.
    With ``carry`` the whole row is kept as ``b``.
    """
    kinds = pool.select("pred_sig", "target").distinct().collect()  # as many as attribute sets
    types = dict(rows.dtypes)
    named = rows.toDF(*[f"_r_{c}" for c in rows.columns])
    out = [*[F.col(f"_r_{c}").alias(c) for c in key], "target", "new"]
    if carry:
        out.append(F.struct(*[F.col(f"_r_{c}").alias(c) for c in rows.columns]).alias("b"))
    parts = []
    for k in kinds:
        clauses = [tuple(c.split(":")) for c in k["pred_sig"].split(",") if c]
        sub = pool.filter((F.col("pred_sig") == k["pred_sig"]) & (F.col("target") == k["target"]))
        fields = [F.get("pred", F.lit(i))[f].alias(f"_{n}{i}") for i in range(len(clauses)) for f, n in (("lo", "lo"), ("hi", "hi"), ("vals", "vals"), ("lo_incl", "li"), ("hi_incl", "hx"))]
        sub = sub.select("unit", "repair_id", "pos", "target", F.col("value").alias("new"), *fields)
        cond = reduce(lambda x, y: x & y, [_matches(i, a, op, types[a]) for i, (a, op) in enumerate(clauses)], F.lit(True))
        kind = types[k["target"]]
        hit = sub.join(named, cond).filter(~comparable(F.col(f"_r_{k['target']}"), kind).eqNullSafe(literal(F.col("new"), kind)))
        parts.append(hit.select("unit", "repair_id", "pos", *out))
    if not parts:
        none = pool.select("unit", "repair_id", "pos", "target", F.col("value").alias("new")).limit(0)
        return none.crossJoin(named.limit(0)).select("unit", "repair_id", "pos", *out)
    return reduce(DataFrame.unionByName, parts)


def support(pool: DataFrame, rows: DataFrame, key: str = "rec_id") -> DataFrame:
    """(repair_id, support): rows that a repair would change; others do nothing."""
    return bind(pool, rows, (key,)).groupBy("repair_id").agg(F.count_distinct(key).alias("support"))


def expand_keys(repair: Repair, rows: DataFrame, key: str = "rec_id") -> DataFrame:
    """A coarse repair as one repair for each record it would change."""
    hit = bind(pool_of(rows.sparkSession, [repair]), rows, (key,))
    return equality_repairs(hit, {key: F.col(key)}, repair.target, F.lit(repair.value), repair.op)


def generalize(pool: DataFrame, rows: DataFrame, attrs: list[str], key: str = "rec_id") -> DataFrame:
    """Fold per-key repairs of one target and value into a predicate of one attribute.

    For each attribute: an equality, if the records agree on it, or a threshold
    (<= or >=), where it covers exactly the same records of ``rows``.
    Returns (target, value, attr, op, bound, n).
    """
    cells = pool.select(F.col("pred")[0]["lo"].alias("_k"), "target", "value").distinct()
    hit = cells.join(rows, F.col("_k") == rows[key].cast("string"))
    found = None
    for a in attrs:
        number = dict(rows.dtypes)[a] not in ("string",)
        got = hit.groupBy("target", "value").agg(F.count("*").alias("n"), F.min(a).alias("lo"), F.max(a).alias("hi"), F.count(a).alias("named"))
        counts = rows.groupBy(F.col(a).alias("_v")).agg(F.count("*").alias("c")).filter("_v is not null")
        options = [("eq", got.filter("lo = hi and named = n"), lambda g: F.col("_v") == F.col("lo"), "lo")]
        if number:
            options += [("le", got.filter("named = n"), lambda g: F.col("_v") <= F.col("hi"), "hi"), ("ge", got.filter("named = n"), lambda g: F.col("_v") >= F.col("lo"), "lo")]
        for op, g, cond, bound in options:
            # Distinct values with counts, not rows, meet the few (target, value) groups.
            total = g.join(counts, cond(g)).groupBy("target", "value", "n", bound).agg(F.sum("c").alias("all")).filter("`all` = n")
            part = total.select("target", "value", F.lit(a).alias("attr"), F.lit(op).alias("op"), F.col(bound).cast("string").alias("bound"), "n")
            found = part if found is None else found.unionByName(part)
    return found


def consensus(pool: DataFrame, rows: DataFrame, key: str = "rec_id", min_votes: int = 2) -> DataFrame:
    """(key, target, new, votes): edits that at least ``min_votes`` tools agree on,
    the most voted for a cell, ties to the smallest value."""
    hit = bind(pool.withColumn("unit", F.lit(0).cast("long")), rows, (key,)).join(pool.select("repair_id", "op").distinct(), "repair_id")
    votes = hit.groupBy(key, "target", "new").agg(F.count_distinct("op").alias("votes")).filter(F.col("votes") >= min_votes)
    best = votes.groupBy(key, "target").agg(F.min_by(F.struct("new", "votes"), F.struct(-F.col("votes"), F.col("new"))).alias("x"))
    return best.select(key, "target", F.col("x.new").alias("new"), F.col("x.votes").alias("votes"))


def clauses_of(row) -> tuple[Clause, ...]:
    return tuple(Clause(c["attr"], c["op"], c["lo"], c["hi"], c["lo_incl"], c["hi_incl"], tuple(c["vals"] or ())) for c in row["pred"])
