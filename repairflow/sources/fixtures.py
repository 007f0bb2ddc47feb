"""Dirty relations with known truth, built from the given tables.

Noise is a function of the key: h(key, salt) is the first eight hexadecimal digits
of an MD5, so every engine builds the same rows.  Each fixture is written once as
SQL over views of the given tables; Spark and other engines differ in a handful of
function names that ``dialect`` fills in.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..session import written
from . import tables

# Words of the part names and types.
ADJECTIVES = ("blue", "cold", "hot", "large", "new", "old", "red", "small")
NOUNS = ("anvil", "bolt", "gear", "gizmo", "plate", "ring", "rod", "widget")
TYPES = ("ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD")

#: The mean of a reading and the 24 before it, in the order in which DuckDB adds the doubles of a frame: rows go into
#: blocks of 16 from the start of their series; of a block that lies inside the frame the sum is taken first and added
#: whole.  Bins of the mean are cut at values that copies of a reading hit exactly, so its last bit counts.
_ADDED = "aggregate({}, {}, (s, x) -> s + x)"
_HEAD = "16 - (at + 8) % 16"  # rows of the frame before its whole block
_BLOCKED = _ADDED.format(f"slice(seen, {_HEAD} + 17, 9 - ({_HEAD}))", _ADDED.format(f"slice(seen, 1, {_HEAD})", "0D") + " + " + _ADDED.format(f"slice(seen, {_HEAD} + 1, 16)", "0D"))
_SMOOTHED = (
    f"select rec_id, station, ts, case when at >= 24 and (at + 8) % 16 >= 7 then {_BLOCKED} else {_ADDED.format('seen', '0D')} end / nullif(n, 0) as truth from ("
    "select event_id as rec_id, event_type as station, ts, cast(row_number() over w - 1 as int) as at, collect_list(coalesce(value, 0D)) over f as seen, count(value) over f as n "
    "from events window w as (partition by event_type order by ts, event_id), f as (partition by event_type order by ts, event_id rows between 24 preceding and current row)) t"
)

SPARK = {
    "smoothed": _SMOOTHED,
    "h": lambda key, salt: f"cast(conv(substr(md5(concat(cast({key} as string), '|', '{salt}')), 1, 8), 16, 10) as bigint)",
    "words": lambda col: f"explode(regexp_extract_all(lower({col}), '[a-z]+', 0))",
    "string": "string",
    "part2": lambda col, i: f"split_part({col}, ' ', {i})",
    "chr": "char",
    "double": "double",
}
DUCK = {
    "smoothed": "select event_id as rec_id, event_type as station, ts, avg(value) over (partition by event_type order by ts, event_id rows between 24 preceding and current row) as truth from events",
    "h": lambda key, salt: f"('0x' || substr(md5(cast({key} as varchar) || '|' || '{salt}'), 1, 8))::bigint",
    "words": lambda col: f"unnest(regexp_extract_all(lower({col}), '[a-z]+'))",
    "string": "varchar",
    "part2": lambda col, i: f"split_part({col}, ' ', {i})",
    "chr": "chr",
    "double": "double",
}


def _misspelt(d: dict, col: str, key: str, salt: str) -> str:
    """One character of a value replaced by another letter."""
    h = d["h"]
    pos = f"cast({h(key, salt + '-at')} % length({col}) as int)"
    return f"concat(substr({col}, 1, {pos}), {d['chr']}(cast(97 + {h(key, salt + '-to')} % 26 as int)), substr({col}, {pos} + 2))"


def catalog(d: dict) -> dict[str, str]:
    """item, noun and type of parts; 5% of the cells wrong, item determines noun."""
    h = d["h"]

    def noisy(col: str, other: str) -> str:
        kind = f"{h('rec_id', col + '-kind')} % 4"
        return (
            f"case when {h('rec_id', col + '-hit')} % 100 >= 5 then {col} when {kind} < 2 then {_misspelt(d, col, 'rec_id', col)} "
            f"when {kind} = 2 then null else {other} end"
        )

    pick = lambda values, salt: "case " + f"{h('rec_id', salt)} % {len(values)} " + " ".join(f"when {i} then '{v}'" for i, v in enumerate(values)) + " end"
    return {
        "catalog_clean": f"select p_partkey as rec_id, p_name as item, {d['part2']('p_name', 2)} as noun, p_type as type, p_brand as brand, p_retailprice as price from part",
        "catalog_dirty": "select rec_id, "
        + noisy("item", f"concat({pick(ADJECTIVES, 'item-other')}, ' ', noun)")
        + " as item, "
        + noisy("noun", pick(NOUNS, "noun-other"))
        + " as noun, "
        + noisy("type", pick(TYPES, "type-other"))
        + " as type, brand, price from catalog_clean",
    }


def words(d: dict, size: int = 1000) -> dict[str, str]:
    """A dictionary of ``size`` words; a tenth of them again with 1 to 3 characters changed."""
    h = d["h"]
    edited = {"words_0": "select rec_id, word, word as w from dictionary where rec_id % 10 = 3"}
    for i in range(3):
        edited[f"words_{i + 1}"] = f"select rec_id, word, case when {h('rec_id', 'edits')} % 3 >= {i} then {_misspelt(d, 'w', 'rec_id', f'edit{i}')} else w end as w from words_{i}"
    return {
        "tokens": f"select distinct w as word from (select {d['words']('text')} as w from documents where lang = 'en') t where length(w) between 4 and 12",
        "dictionary": f"select cast(rn as bigint) as rec_id, word from (select word, row_number() over (order by md5(word), word) as rn from tokens) t where rn <= {size}",
        **edited,
        "words_dirty": "select rec_id, word, word as truth from dictionary union all select rec_id + 100000 as rec_id, w as word, word as truth from words_3",
    }


def series(d: dict) -> dict[str, str]:
    """Smoothed readings of stations; one in fifty too large or clipped."""
    k = d["h"]("rec_id", "spike") + " % 100"
    return {
        "series_clean": d["smoothed"],
        "series_dirty": f"select rec_id, station, ts, case when {k} < 1 then truth * 20 when {k} = 1 then cast(0.01 as double) else truth end as reading, truth from series_clean",
    }


WIDE_ATTRS = ("c_name", "c_mktsegment", "n_name", "r_name", "p_name", "p_brand", "s_name", "o_orderpriority")
WIDE_FDS = (
    "c_custkey -> c_name", "c_custkey -> c_mktsegment", "c_name -> n_name", "n_name -> r_name",
    "p_partkey -> p_name", "p_partkey -> p_brand", "s_suppkey -> s_name", "o_orderkey -> o_orderpriority",
)


def wide(d: dict) -> dict[str, str]:
    """The seven-way join with eight dependencies; 2% of the right-hand cells wrong."""
    h, s = d["h"], d["string"]
    parts = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "cast(l_quantity as bigint)", "cast(round(l_extendedprice * 100) as bigint)"]
    key = "md5(concat_ws('|', " + ", ".join(f"cast({p} as {s})" for p in parts) + "))"

    def noisy(col: str) -> str:
        kind = f"{h('rec_id', col + '-kind')} % 3"
        return f"case when {h('rec_id', col + '-hit')} % 100 >= 2 then {col} when {kind} = 0 then {_misspelt(d, col, 'rec_id', col)} when {kind} = 1 then null else concat({col}, 'x') end as {col}"

    keys = "rec_id, c_custkey, p_partkey, s_suppkey, o_orderkey, o_orderdate"
    return {
        "wide_clean": f"select {key} as rec_id, c_custkey, c_name, c_mktsegment, n_name, r_name, p_partkey, p_name, p_brand, s_suppkey, s_name, o_orderkey, o_orderpriority, o_orderdate "
        "from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey "
        "join part on l_partkey = p_partkey join supplier on l_suppkey = s_suppkey",
        "wide_dirty": f"select {keys}, " + ", ".join(noisy(a) for a in WIDE_ATTRS) + " from wide_clean",
    }


SPLIT_ROWS = 10_000


def split(d: dict, rows: int = SPLIT_ROWS) -> dict[str, str]:
    """Two name fields, item and noun; 5% bad, half of those run together in one field."""
    h = d["h"]
    up = f"upper({d['part2']('p_name', 2)})"
    parts = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "cast(l_quantity as bigint)", "cast(round(l_extendedprice * 100) as bigint)"]
    key = "md5(concat_ws('|', " + ", ".join(f"cast({p} as {d['string']})" for p in parts) + "))"
    bad = f"{h('rec_id', 'bad')} % 100 < 5"
    joined = f"{h('rec_id', 'glue')} % 2 = 0"
    sep = f"case {h('rec_id', 'sep')} % 3 when 0 then ':' when 1 then ',' else '-' end"
    return {
        "split_clean": f"select cast(rn as bigint) as rec_id, p_name as t1, {up} as t2 from (select p_name, row_number() over (order by {key}) as rn from lineitem join part on l_partkey = p_partkey) t where rn <= {rows}",
        "split_bad": f"select rec_id, t1, t2, case when {bad} and {h('rec_id', 'which')} % 2 = 0 then {_misspelt(d, 't1', 'rec_id', 'str1')} else t1 end as s1, "
        f"case when {bad} and {h('rec_id', 'which')} % 2 = 1 then 'OTHER' else t2 end as s2, {bad} and {joined} as glued from split_clean",
        "split_dirty": f"select rec_id, case when glued then concat(s1, {sep}, s2) else s1 end as str1, case when glued then '' else s2 end as str2, t1, t2 from split_bad",
    }


FIXTURES = {"catalog": catalog, "words": words, "series": series, "wide": wide, "split": split}
_NEEDS = {
    "catalog": ("part",), "words": ("documents",), "series": ("events",), "wide": ("lineitem", "orders", "customer", "nation", "region", "part", "supplier"), "split": ("lineitem", "part"),
}


def ctes(name: str, dialect: dict = DUCK) -> str:
    """The fixture as a WITH list, to which a query can be appended."""
    return "with " + ", ".join(f"{k} as ({v})" for k, v in FIXTURES[name](dialect).items())


def build(spark: SparkSession, sf_dir: str, fixture: str, table: str) -> DataFrame:
    """One table of a fixture as a DataFrame."""
    tables.register_views(spark, sf_dir, _NEEDS[fixture])
    df = spark.sql(ctes(fixture, SPARK) + f" select * from {table}")
    if fixture == "split":
        return _first_rows(df, table)
    # Thrice nested CASE expressions, pushed into filters, would outgrow generated code.
    return written(df, table) if fixture == "words" else df


_LIMIT = "spark.sql.optimizer.windowGroupLimitThreshold"


def _first_rows(df: DataFrame, table: str) -> DataFrame:
    """A table of the first rows of a global order, written.  Each task passes on its own first rows
    only; by default Spark does so up to 1,000 rows, and else sorts the whole join in one task."""
    conf = df.sparkSession.conf
    before = conf.get(_LIMIT)
    try:
        conf.set(_LIMIT, str(max(int(before), SPLIT_ROWS)))
        return written(df, table)
    finally:
        conf.set(_LIMIT, before)
