"""The given tables as sequences, and the same as SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from bitparse.sources import sequences


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spread(df: DataFrame) -> DataFrame:
    """df over all cores, where its files give too few tasks for kernels that cost far more than moving the rows."""
    n = 4 * df.sparkSession.sparkContext.defaultParallelism
    return df if df.rdd.getNumPartitions() >= n else df.repartition(n)


def ranked(df: DataFrame, symbol: Column) -> DataFrame:
    """df with ``sym``, the rank of a column of few values (statuses, flags) among them."""
    named = df.withColumn("__v", symbol)
    values = named.select("__v").distinct()
    return named.join(F.broadcast(values.select("__v", F.row_number().over(Window.orderBy("__v")).alias("sym"))), "__v")


def documents(spark, sf_dir):
    return sequences.from_text(spread(read(spark, sf_dir, "documents").select("doc_id", "text")), "doc_id", "text")


def pages(spark, sf_dir):
    return sequences.from_text(spread(read(spark, sf_dir, "pages").select("page_id", "html")), "page_id", "html")


def benchmark(spark, sf_dir):
    return sequences.from_text(read(spark, sf_dir, "benchmark"), "item_id", "text")


def names(spark, sf_dir):
    return sequences.from_text(read(spark, sf_dir, "part"), "p_partkey", "p_name")


def conversation_text(spark, sf_dir) -> DataFrame:
    """(conv_id, text): the first letter of each role and the text, by turn."""
    rows = F.array_sort(F.collect_list(F.struct("turn", F.concat(F.substring("role", 1, 1), F.coalesce("text", F.lit(""))).alias("t"))))
    return read(spark, sf_dir, "conversations").groupBy("conv_id").agg(rows.alias("r")).select("conv_id", F.array_join(F.transform("r", lambda r: r["t"]), "").alias("text"))


def conversations(spark, sf_dir):
    return sequences.from_text(conversation_text(spark, sf_dir), "conv_id", "text")


def events(spark, sf_dir):
    return sequences.from_events(ranked(read(spark, sf_dir, "events"), F.col("event_type")), "user_id", ["ts", "event_id"], F.col("sym"))


def event_keys(spark, sf_dir):
    return sequences.from_events(read(spark, sf_dir, "events"), "user_id", ["ts", "event_id"], F.get_json_object("props", "$.k").cast("int") + 1)


def orders(spark, sf_dir):
    return sequences.from_events(ranked(read(spark, sf_dir, "orders"), F.col("o_orderstatus")), "o_custkey", ["o_orderdate", "o_orderkey"], F.col("sym"))


_LINE = ["l_shipdate", "l_orderkey", "l_linenumber", "l_suppkey", "l_quantity"]


def lineitem(spark, sf_dir):
    return sequences.from_events(ranked(read(spark, sf_dir, "lineitem"), F.concat("l_returnflag", "l_linestatus")), "l_partkey", _LINE, F.col("sym"))


def supplier_lines(spark, sf_dir):
    """Of each supplier the return flags and statuses of its lines, in order: long sequences of few symbols."""
    return sequences.from_events(ranked(read(spark, sf_dir, "lineitem"), F.concat("l_returnflag", "l_linestatus")), "l_suppkey", ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_extendedprice"], F.col("sym"))


def days(spark, sf_dir) -> DataFrame:
    """(x): the days from the first to ship to each day on which lines were shipped."""
    own = read(spark, sf_dir, "lineitem").select(F.to_date("l_shipdate").alias("d")).distinct()
    return own.crossJoin(F.broadcast(own.agg(F.min("d").alias("first")))).select(F.date_diff("d", "first").cast("long").alias("x"))


def part_keys(spark, sf_dir) -> DataFrame:
    """(x): the keys of parts that were sold."""
    return read(spark, sf_dir, "lineitem").select(F.col("l_partkey").cast("long").alias("x")).distinct()


def taxes(spark, sf_dir, least: int = 2) -> DataFrame:
    """(seq_id): 2 more than each tax in hundredths, from ``least`` on."""
    return read(spark, sf_dir, "lineitem").select((F.round(F.col("l_tax") * 100).cast("long") + 2).alias("seq_id")).distinct().filter(F.col("seq_id") >= least)


def months(spark, sf_dir) -> DataFrame:
    """(seq_id): 2 more than each month of the year in which lines were shipped."""
    return read(spark, sf_dir, "lineitem").select((F.month("l_shipdate").cast("long") + 2).alias("seq_id")).distinct()


#: The same as SQL.
DAYS = "(select distinct date_diff('day', (select min(l_shipdate) from lineitem), l_shipdate)::bigint as x from lineitem)"
PART_KEYS = "(select distinct l_partkey::bigint as x from lineitem)"
TAXES = "(select distinct round(l_tax * 100)::bigint + 2 as l from lineitem)"
MONTHS = "(select distinct month(l_shipdate)::bigint + 2 as l from lineitem)"


def suppliers(spark, sf_dir):
    return sequences.from_events(read(spark, sf_dir, "lineitem"), "l_partkey", _LINE, F.col("l_suppkey"))


def embeddings(spark, sf_dir):
    return sequences.from_vectors(read(spark, sf_dir, "embeddings"), "vec_id", "embedding")


ALL = {f.__name__: f for f in (documents, pages, benchmark, names, conversations, events, event_keys, orders, lineitem, suppliers, embeddings)}


def _by_key(key: str, order: str, symbol: str, table: str) -> str:
    return f"select {key}::bigint as seq_id, (row_number() over (partition by {key} order by {order}))::int as i, ({symbol})::bigint as s from {table}"


def _chars(key: str, text: str, table: str) -> str:
    return f"select seq_id, i::int as i, unicode(c)::bigint as s from (select {key}::bigint as seq_id, unnest(string_split({text}, '')) as c, generate_subscripts(string_split({text}, ''), 1) as i from {table}) where c <> ''"


_RANK = "(select v, row_number() over (order by v) as sym from (select distinct {v} as v from {t}))"

#: sym(seq_id, i, s) of each table.
SYM = {
    "events": _by_key("user_id", "ts, event_id", "sym", f"events join {_RANK.format(v='event_type', t='events')} on v = event_type"),
    "event_keys": _by_key("user_id", "ts, event_id", "cast(json_extract_string(props, '$.k') as int) + 1", "events"),
    "orders": _by_key("o_custkey", "o_orderdate, o_orderkey", "sym", f"orders join {_RANK.format(v='o_orderstatus', t='orders')} on v = o_orderstatus"),
    "lineitem": _by_key("l_partkey", ", ".join(_LINE), "sym", f"lineitem join {_RANK.format(v='l_returnflag || l_linestatus', t='lineitem')} on v = l_returnflag || l_linestatus"),
    "suppliers": _by_key("l_partkey", ", ".join(_LINE), "l_suppkey", "lineitem"),
    "embeddings": "select vec_id::bigint as seq_id, i::int as i, (least(15, greatest(0, floor((x::double + 1) * 8))) + 1)::bigint as s from (select vec_id, unnest(embedding) as x, generate_subscripts(embedding, 1) as i from embeddings)",
    "documents": _chars("doc_id", "text", "documents"),
    "pages": _chars("page_id", "html", "pages"),
    "benchmark": _chars("item_id", "text", "benchmark"),
    "names": _chars("p_partkey", "p_name", "part"),
    "conversations": _chars("conv_id", "text", "(select conv_id, string_agg(substr(role, 1, 1) || coalesce(text, ''), '' order by turn) as text from conversations group by conv_id)"),
}


#: Key, text and table of sequences whose substrings SQL takes from the text.
TEXTS = {"benchmark": ("item_id", "text", "benchmark"), "names": ("p_partkey", "p_name", "part")}


def copies_sql(name: str) -> str:
    """CTEs sym, seq, gram and copies (seq_id, i, len, dist): right-most earlier copies of all substrings."""
    if name in TEXTS:
        key, text, source = TEXTS[name]
        return f"""sym as materialized ({SYM[name]}),
seq as materialized (select {key}::bigint as seq_id, {text} as syms, length({text})::int as n from {source}),
start as (select seq_id, syms, n, unnest(range(1, n + 1))::int as i from seq),
gram as (select seq_id, i, len, substr(syms, i, len) as gram from (select seq_id, syms, i, unnest(range(1, n - i + 2))::int as len from start)),
copies as materialized (select * from (select seq_id, i, len, i - lag(i) over (partition by seq_id, len, gram order by i) as dist from gram) where dist is not null)"""
    return f"""sym as materialized ({SYM[name]}),
seq as materialized (select seq_id, list(s order by i) as syms, count(*)::int as n from sym group by seq_id),
start as (select seq_id, syms, n, unnest(range(1, n + 1))::int as i from seq),
gram as (select seq_id, i, len, syms[i:i + len - 1] as gram from (select seq_id, syms, i, unnest(range(1, n - i + 2))::int as len from start)),
copies as materialized (select * from (select seq_id, i, len, i - lag(i) over (partition by seq_id, len, gram order by i) as dist from gram) where dist is not null)"""


def edges_sql(name: str, f: str, g: str) -> str:
    """The same, and priced edges (seq_id, i, j, kind, dist, len, sym, bits). f and g: SQL of code lengths with {x}."""
    zero = f.replace("{x}", "0")
    return f"""{copies_sql(name)},
edges as materialized (
select seq_id, i, i + len as j, 'copy' as kind, dist, len, null::int as sym, ({f.replace('{x}', 'dist')} + {g.replace('{x}', 'len')})::bigint as bits from copies
union all select seq_id, i, i + 1, 'literal', 0, 1, s::int, ({zero} + {g.replace('{x}', 's')})::bigint from sym)"""


def optimum_sql(edges: str = "edges", bits: str = "bits") -> str:
    """CTEs back, walk and best (seq_id, bits): the shortest paths over a relation of edges."""
    return f"""back as materialized (select seq_id, j, list({{'i': i, 'bits': {bits}}}) as steps from {edges} group by seq_id, j),
walk as (
select distinct seq_id, 1 as j, [0::bigint] as costs from back
union all select w.seq_id, w.j + 1, list_append(w.costs, list_min(list_transform(b.steps, lambda e: w.costs[e.i] + e.bits))) from walk w join back b on b.seq_id = w.seq_id and b.j = w.j + 1),
best as (select seq_id, max_by(costs[-1], j)::bigint as bits from walk group by seq_id)"""
