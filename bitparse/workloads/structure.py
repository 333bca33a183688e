"""Codes, sequences, repeats and graphs."""

from __future__ import annotations

from pyspark.sql import functions as F

from bitparse.functions import codes
from bitparse.operators import measures, repeats, stars
from bitparse.sources import sequences
from bitparse.workloads import tables

QUERIES, ORACLE_SQL = {}, {}


def add(name, query, sql=None):
    QUERIES[name] = query
    if sql:
        ORACLE_SQL[name] = sql


def _lengths_sql(values, names=codes.STANDARD):
    return " union all ".join(f"select '{n}' as code, x, {codes.code(n).sql('x')}::bigint as bits from {values}" for n in names)


# Codes: the lengths of the numbers of days on which lines were shipped.
_LENGTHS = _lengths_sql(tables.DAYS)
_lengths = lambda s, d: codes.lengths_of(tables.days(s, d))
add("code_lengths", _lengths, _LENGTHS)
add("code_plateaus", lambda s, d: codes.plateau_table(_lengths(s, d)), f"select code, (row_number() over (partition by code order by min(x)))::bigint as k, min(x) as lo, max(x) as hi, bits from ({_LENGTHS}) group by code, bits")
add("code_monotone", lambda s, d: codes.is_monotone(_lengths(s, d)), f"select code, bool_and(ok) as monotone from (select code, coalesce(bits >= lag(bits) over (partition by code order by x), true) as ok from ({_LENGTHS})) group by code")
add("code_log_ratio", lambda s, d: codes.log_ratio(_lengths(s, d)), f"select code, round(min(bits / log2(x + 1)), 6) as least, round(max(bits / log2(x + 1)), 6) as most from ({_LENGTHS}) where x >= 1 group by code")
#: The same codes, with digits enough for the largest size.
_WIDER = tuple("fixed17" if n == "fixed13" else n for n in codes.STANDARD)
_SIZES = (16, 256, 1024, 4096, 65_536)


def _q_counts(s, d):
    """How many lengths there are up to each size, among the keys of parts."""
    sizes = F.explode(F.array(*map(F.lit, _SIZES)))
    own = tables.part_keys(s, d).filter(F.col("x").between(1, _SIZES[-1]))
    return codes.lengths_of(own, _WIDER).withColumn("n", sizes).filter("x <= n").groupBy("code", "n").agg(F.countDistinct("bits").alias("q"))


add("code_q_counts", _q_counts, f"select code, n, count(distinct bits) as q from ({_lengths_sql(f'(select x from {tables.PART_KEYS} where x <= {_SIZES[-1]})', _WIDER)}), (select unnest({list(_SIZES)}) as n) where x between 1 and n group by code, n")

# Sequences: length, alphabet, and a digest of all symbols in order.


def _described(name):
    def query(s, d):
        joined = F.array_join(F.transform("syms", lambda x: x.cast("string")), ",")
        return tables.ALL[name](s, d).select("seq_id", F.col("n").cast("long").alias("n"), F.size(F.array_distinct("syms")).cast("long").alias("sigma"), F.md5(joined.cast("binary")).alias("digest"))

    return query


for _name in tables.SYM:
    add(f"seq_{_name}", _described(_name), f"select seq_id, count(*)::bigint as n, count(distinct s)::bigint as sigma, md5(string_agg(s::varchar, ',' order by i)) as digest from ({tables.SYM[_name]}) group by seq_id")
add("seq_document_bytes", lambda s, d: sequences.from_text(tables.read(s, d, "documents"), "doc_id", "text", "byte").select("seq_id", F.col("n").cast("long").alias("n")), "select doc_id::bigint as seq_id, octet_length(encode(text))::bigint as n from documents")
add("alphabet_global", lambda s, d: sequences.alphabet(tables.documents(s, d)).select(F.col("symbol").cast("long").alias("symbol"), "rank", "count"), f"select s as symbol, row_number() over (order by s) as rank, count(*) as count from ({tables.SYM['documents']}) group by s")


def _remapped(s, d):
    own = tables.suppliers(s, d)
    both = sequences.explode(sequences.remap(own)).withColumnRenamed("s", "global")
    return both.join(sequences.explode(sequences.remap(own, "sequence")).withColumnRenamed("s", "own"), ["seq_id", "i"])


add("alphabet_remap", _remapped, f"select seq_id, i, (dense_rank() over (order by s))::int as global, (dense_rank() over (partition by seq_id order by s))::int as own from ({tables.SYM['suppliers']})")

# Repeats, by grams over short sequences; whole documents by the kernel.


def _sym(name, s, d):
    return sequences.explode(tables.ALL[name](s, d))


def _copies(name, s, d):
    return repeats.prev_occurrence(repeats.grams(_sym(name, s, d)))


def _edges(name, s, d, f="gamma", g="gamma"):
    return stars.edges(_copies(name, s, d), _sym(name, s, d), f, g)


add("gram_prev_occurrence", lambda s, d: _copies("events", s, d), f"with {tables.copies_sql('events')} select * from copies")
add("longest_prev_match", lambda s, d: repeats.longest_prev_match(_copies("events", s, d)), f"with {tables.copies_sql('events')} select seq_id, i, max(len) as len, max_by(dist, len) as dist from copies group by seq_id, i")
_SUFFIX = f"sym as ({tables.SYM['orders']}), seq as (select seq_id, list(s order by i) as syms, count(*)::int as n from sym group by seq_id), start as (select seq_id, syms, n, unnest(range(1, n + 1))::int as i from seq)"
add(
    "suffix_ranks", lambda s, d: repeats.suffix_order(tables.orders(s, d)),
    f"""with {_SUFFIX}, placed as (select seq_id, i, syms[i:] as x, row_number() over (partition by seq_id order by syms[i:]) as rank, lag(syms[i:]) over (partition by seq_id order by syms[i:]) as y from start)
select seq_id, i, rank::int as rank, coalesce(list_max(list_transform(range(0, least(len(x), len(y)) + 1), lambda k: case when x[1:k] = y[1:k] then k else 0 end)), 0)::bigint as lcp from placed""",
)
add("longest_repeat_events", lambda s, d: measures.longest_repeat(tables.events(s, d)).select("seq_id", "longest"), f"with {tables.copies_sql('events')} select seq_id, max(len)::bigint as longest from copies group by seq_id")
add("longest_repeat_documents", lambda s, d: measures.longest_repeat(tables.documents(s, d)))

# The graph of parsing steps.
_GAMMA = codes.gamma().sql("{x}")
_G = tables.edges_sql("events", _GAMMA, _GAMMA)
add("full_graph_edges", lambda s, d: _edges("events", s, d), f"with {_G} select * from edges")
add("full_graph_size", lambda s, d: _edges("lineitem", s, d).groupBy("seq_id", "kind").agg(F.count("*").alias("edges"), F.sum("bits").alias("bits")), f"with {tables.edges_sql('lineitem', _GAMMA, _GAMMA)} select seq_id, kind, count(*) as edges, sum(bits)::bigint as bits from edges group by seq_id, kind")
add("star_contiguity", lambda s, d: measures.contiguous(_edges("events", s, d)), f"with {_G}, star as (select seq_id, i, max(j) - i - count(distinct j) as missing from edges group by seq_id, i) select seq_id, count(*) filter (missing <> 0) as gaps from star group by seq_id")
add(
    "star_monotone", lambda s, d: measures.monotone(_edges("events", s, d)),
    f"with {_G}, x as (select seq_id, bits < lag(bits) over (partition by seq_id, i order by j) as f, bits < lag(bits) over (partition by seq_id, j order by i desc) as b from edges where kind = 'copy') select seq_id, count(*) filter (f) as forward, count(*) filter (b) as backward from x group by seq_id",
)
_NEXT = {"d": "df", "l": "dg", "right": "df or dg", "cost": "dc"}


def _pruned(name):
    """CTEs up to ahead: the copies, and whether the next longer one costs more in distance, in length, in all."""
    more = lambda c: f"coalesce({_GAMMA.replace('{x}', 'n' + c)} > {_GAMMA.replace('{x}', c)}, true)"
    return f"""{tables.edges_sql(name, _GAMMA, _GAMMA)},
beside as materialized (select *, lead(dist) over w as ndist, lead(len) over w as nlen, lead(bits) over w as nbits from edges where kind = 'copy' window w as (partition by seq_id, i order by j)),
ahead as materialized (select seq_id, i, j, kind, dist, len, sym, bits, {more('dist')} as df, {more('len')} as dg, coalesce(nbits > bits, true) as dc from beside)"""


_PRUNE = _pruned("events")
for _rule, _keep in _NEXT.items():
    for _name in ("orders", "names"):
        add(f"maximal_edges_{_rule}" + ("" if _name == "orders" else "_names"), lambda s, d, r=_rule, n=_name: stars.prune_edges(_edges(n, s, d), "gamma", "gamma", r), f"with {_pruned(_name)} select seq_id, i, j, kind, dist, len, sym, bits from ahead where {_keep} union all select * from edges where kind = 'literal'")
add(
    "maximal_edges_left", lambda s, d: stars.prune_edges(_edges("orders", s, d), "gamma", "gamma", "left"),
    f"with {tables.edges_sql('orders', _GAMMA, _GAMMA)}, beside as (select *, min(bits) over (partition by seq_id, j order by i rows between unbounded preceding and 1 preceding) as least from edges where kind = 'copy') select seq_id, i, j, kind, dist, len, sym, bits from beside where least is null or bits < least union all select * from edges where kind = 'literal'",
)
_LONGEST = "(select max(n) + 1 from seq)"
_Q = f"(select n, count(distinct b) as q from (select unnest(range(1, {_LONGEST})) as n), (select x, 2 * length(bin(x + 1)) - 1 as b from (select unnest(range(1, {_LONGEST})) as x)) where x <= n group by n)"
add(
    "max_degree", lambda s, d: measures.degree(stars.prune_edges(_edges("events", s, d), "gamma", "gamma"), "gamma", "gamma"),
    f"with {_PRUNE}, kept as (select seq_id, i from ahead where df or dg union all select seq_id, i from edges where kind = 'literal'), deg as (select seq_id, i, count(*) as k from kept group by seq_id, i), own as (select seq_id, sum(k)::bigint as n_edges, max(k) as max_degree, max(i) as n from deg group by seq_id) select seq_id, n_edges, max_degree, (2 * q)::bigint as bound from own join {_Q} using (n)",
)


def _max_lcp(s, d):
    price = codes.gamma().column(F.col("dist"))
    pairs = _sym("orders", s, d).select("seq_id", "i").alias("a").join(_sym("orders", s, d).select("seq_id", F.col("i").alias("p")), "seq_id").filter("p < i")
    seq = tables.orders(s, d).select("seq_id", "syms")
    both = pairs.join(seq, "seq_id").select("seq_id", "i", (F.col("i") - F.col("p")).alias("dist"), F.slice("syms", F.col("i"), F.size("syms")).alias("x"), F.slice("syms", F.col("p"), F.size("syms") - F.col("i") + 1).alias("y"))
    differs = F.array_position(F.zip_with("x", "y", lambda a, b: a != b), True)
    match = F.when(differs == 0, F.size("x")).otherwise(differs - 1).cast("long")
    return both.select("seq_id", "i", price.alias("plateau"), match.alias("lcp")).filter("lcp > 0").groupBy("seq_id", "i", "plateau").agg(F.max("lcp").alias("lcp"))


add(
    "max_lcp_window", _max_lcp,
    f"with {_SUFFIX}, pairs as (select a.seq_id, a.i, a.i - b.i as dist, a.syms[a.i:] as x, a.syms[b.i:] as y from start a join start b on a.seq_id = b.seq_id and b.i < a.i), l as (select seq_id, i, {_GAMMA.replace('{x}', 'dist')} as plateau, list_max(list_transform(range(0, len(x) + 1), lambda k: case when x[1:k] = y[1:k] then k else 0 end)) as lcp from pairs) select seq_id, i, plateau::bigint as plateau, max(lcp)::bigint as lcp from l where lcp > 0 group by seq_id, i, plateau",
)
add("block_star_recall", lambda s, d: measures.star_recall(tables.events(s, d)), f"with {_PRUNE} select seq_id, count(*) filter (df) as d_maximal, count(*) filter (df) as found, 0::bigint as invalid from ahead group by seq_id")
add("completeness_of_copies", lambda s, d: measures.completeness(repeats.grams(_sym("orders", s, d)).select(F.col("gram").alias("phrase"))), "select 0::bigint as prefix, 0::bigint as suffix")
