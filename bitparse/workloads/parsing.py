"""Parsers: optimum, greedy, heuristics, the growing and the fixed dictionary, bounds, sizes and round trips."""

from __future__ import annotations

from pyspark.sql import functions as F

from bitparse.functions import codes
from bitparse.operators import bits, chunks, families, lz78, measures, parsers, shortest, stars
from bitparse.sources import sequences
from bitparse.workloads import structure, tables

QUERIES, ORACLE_SQL = {}, {}


def add(name, query, sql=None):
    QUERIES[name] = query
    if sql:
        ORACLE_SQL[name] = sql


_SQL = {n: codes.code(n).sql("{x}") for n in ("gamma", "delta", "fibonacci", "varbyte", "omega", "nibble", "rice2", "fixed13")}
_PAIRS = {"gamma": ("gamma", "gamma"), "delta": ("delta", "delta"), "fibonacci": ("fibonacci", "fibonacci"), "varbyte": ("varbyte", "varbyte"), "mixed": ("delta", "fibonacci")}


def totals(name, parser="optimal", f="gamma", g="gamma", window=None):
    return lambda s, d: parsers.run(tables.ALL[name](s, d), (parser,), f, g, window, phrases=False, work=False).select("seq_id", F.col("n").cast("long").alias("n"), "bits", F.col("counters")["phrases"].alias("phrases"))


def optimum(name, f="gamma", g="gamma", window=None):
    """Bits of the optimum: the same as SQL, on the full graph."""
    near = f" where kind = 'literal' or dist <= {window}" if window else ""
    sql = f"with recursive {tables.edges_sql(name, _SQL[f], _SQL[g])}, used as (select * from edges{near}), {tables.optimum_sql('used')} select seq_id, bits from best"
    return (lambda s, d: totals(name, "optimal", f, g, window)(s, d).select("seq_id", "bits")), sql


# Whole documents and pages, by the kernel.
for _key, (_f, _g) in _PAIRS.items():
    add(f"optimal_bits_{_key}", totals("documents", "optimal", _f, _g))
add("optimal_bits_pages", totals("pages"))
add("optimal_bits_conversations", totals("conversations"))
for _name in ("documents", "pages"):  # the same by steps made block by block
    add(f"optimal_block_{_name}", totals(_name, "optimal_block"))
add("windowed_optimal_documents", totals("documents", window=1024))
for _parser in ("greedy", "greedy_triple", "lazy", "fewest", "length_only", "ratio_greedy"):
    add(f"{_parser}_documents", totals("documents", _parser))
# Short sequences, against shortest paths on the full graph in SQL.
for _key, (_f, _g) in _PAIRS.items():
    add(f"optimal_bits_events_{_key}", *optimum("events", _f, _g))
for _name in ("event_keys", "orders", "lineitem", "suppliers", "embeddings"):
    add(f"optimal_bits_{_name}", *optimum(_name))
# Whole texts of moderate length, character by character.
for _key, (_f, _g) in _PAIRS.items():
    add(f"optimal_bits_benchmark_{_key}", *optimum("benchmark", _f, _g))
add("optimal_bits_names", *optimum("names"))
for _name in ("benchmark", "names"):
    add(f"optimal_block_{_name}", lambda s, d, n=_name: totals(n, "optimal_block")(s, d).select("seq_id", "bits"), optimum(_name)[1])
add("windowed_optimal_benchmark", *optimum("benchmark", window=64))
for _w in (8, 16):
    add(f"windowed_optimal_w{_w}", *optimum("events", window=_w))


def _catalyst(name, rule=None):
    """The whole optimum inside Catalyst: lag, lead and a fold."""

    def query(s, d):
        priced = structure._edges(name, s, d)
        return shortest.fold_costs(stars.prune_edges(priced, "gamma", "gamma", rule) if rule else priced)

    return query


add("optimal_fold_full", _catalyst("orders"), optimum("orders")[1])
add("optimal_fold_pruned", _catalyst("orders", "right"), optimum("orders")[1])


def _full_vs_pruned(s, d):
    own = parsers.compare(tables.events(s, d), parsers=("optimal_full", "optimal_pruned", "optimal_block"))
    return own.select("seq_id", F.col("optimal_full").alias("full"), F.col("optimal_pruned").alias("pruned"), F.col("optimal_block").alias("block"))


add("optimal_full_vs_pruned", _full_vs_pruned, optimum("events")[1].replace("select seq_id, bits from best", 'select seq_id, bits as "full", bits as pruned, bits as block from best'))


def _phrases(s, d):
    parse = parsers.explode(parsers.optimal(tables.events(s, d)))
    return parse.groupBy("seq_id").agg(F.sum("len").alias("symbols"), F.sum("bits").alias("bits"), F.min("start").cast("long").alias("first"))


add("optimal_parse_phrases", _phrases, optimum("events")[1].replace("select seq_id, bits from best", "select seq_id, (select n from seq where seq.seq_id = best.seq_id)::bigint as symbols, bits, 1::bigint as first from best"))

# Greedy parsing: a walk along the longest matches.


def _walk(name, f="gamma", g="gamma"):
    zero = _SQL[f].replace("{x}", "0")
    return f"""with recursive {tables.copies_sql(name)},
longest as materialized (select seq_id, i, max(len) as len, max_by(dist, len) as dist from copies group by seq_id, i),
step as materialized (select sym.seq_id, sym.i, case when len >= 2 then len else 1 end as len, case when len >= 2 then {_SQL[f].replace('{x}', 'dist')} + {_SQL[g].replace('{x}', 'len')} else {zero} + {_SQL[g].replace('{x}', 's')} end as bits from sym left join longest using (seq_id, i)),
walk as (select seq_id, i, len, bits from step where i = 1 union all select s.seq_id, s.i, s.len, s.bits from walk w join step s on s.seq_id = w.seq_id and s.i = w.i + w.len)"""


for _name in ("events", "orders", "lineitem", "benchmark", "names"):
    add(f"greedy_bits_{_name}", totals(_name, "greedy"), f"{_walk(_name)} select seq_id, sum(len)::bigint as n, sum(bits)::bigint as bits, count(*)::bigint as phrases from walk group by seq_id")
add(
    "greedy_phrases", lambda s, d: parsers.explode(parsers.greedy(tables.events(s, d))).select("seq_id", "start", "len", "bits"),
    f"{_walk('events')} select seq_id, i as start, len::int as len, bits::bigint as bits from walk",
)


def _triples(s, d):
    return parsers.explode(parsers.run(tables.events(s, d), ("greedy_triple",))).select("seq_id", "start", "len", "next")


add(
    "greedy_triple_phrases", _triples,
    f"""with recursive {tables.copies_sql('events')}, longest as materialized (select seq_id, i, max(len) as len from copies group by seq_id, i),
step as materialized (select sym.seq_id, sym.i, least(coalesce(len, 0), n - sym.i) + 1 as len from sym join seq using (seq_id) left join longest using (seq_id, i)),
walk as (select * from step where i = 1 union all select s.* from walk w join step s on s.seq_id = w.seq_id and s.i = w.i + w.len)
select w.seq_id, w.i as start, w.len::int as len, s::int as next from walk w join sym on sym.seq_id = w.seq_id and sym.i = w.i + w.len - 1""",
)
for _name, _query in (("events", "fewest_phrases"), ("benchmark", "fewest_phrases_benchmark"), ("names", "fewest_phrases_names")):
    add(_query, lambda s, d, n=_name: totals(n, "fewest")(s, d).select("seq_id", "phrases"), f"with recursive {tables.edges_sql(_name, _SQL['gamma'], _SQL['gamma'])}, {tables.optimum_sql(bits='1')} select seq_id, bits as phrases from best")


def _fixed(s, d):
    own = parsers.compare(tables.events(s, d), "fixed13", "fixed13", ("greedy_copy", "optimal_full"))
    return own.select("seq_id", F.col("greedy_copy").alias("greedy"), F.col("optimal_full").alias("optimal"))


add("fixed_code_equality", _fixed, optimum("events", "fixed13", "fixed13")[1].replace("select seq_id, bits from best", "select seq_id, bits as greedy, bits as optimal from best"))


def _heuristics(s, d):
    names = ("optimal", "greedy", "lazy", "ratio_greedy", "length_only", "iterated_entropy", "greedy_triple", "fewest")
    return parsers.compare(tables.events(s, d), parsers=names)


add("parser_comparison", _heuristics)
add("iterated_entropy_events", totals("events", "iterated_entropy"))

# Gaps and bounds.


def _gap_sql(name):
    both = optimum(name)[1].replace("with recursive ", "").replace(" select seq_id, bits from best", "")
    walk = _walk(name).replace("with recursive ", "").replace(tables.copies_sql(name) + ",\n", "").replace("walk as", "parse as").replace("from walk w", "from parse w")
    return f"with recursive {both}, {walk}, own as (select p.seq_id, sum(p.len)::bigint as n, sum(p.bits)::bigint as greedy, max(best.bits) as optimal from parse p join best on best.seq_id = p.seq_id group by p.seq_id)"


def _gap(name):
    def query(s, d):
        r6 = lambda c: F.round(F.col(c), 6).alias(c)
        return measures.gap(tables.ALL[name](s, d)).select("seq_id", F.col("n").cast("long").alias("n"), "greedy", "optimal", r6("ratio"), r6("bound"), "within")

    return query


_SELECT_GAP = "select seq_id, n, greedy, optimal, round(greedy / optimal, 6) as ratio, round((2 * length(bin(n + 1)) - 1) * 2 / 2.0, 6)::double as bound, greedy / optimal <= (2 * length(bin(n + 1)) - 1) as within from own"
for _name in ("events", "orders", "benchmark", "names"):
    add(f"gap_ratio_{_name}", _gap(_name), f"{_gap_sql(_name)} {_SELECT_GAP}")
add("gap_ratio_documents", _gap("documents"))


def _gap_spread(s, d):
    own = measures.gap(tables.events(s, d))
    at = lambda p: F.round(F.percentile("ratio", F.lit(p)), 6)
    return own.agg(at(0.5).alias("median"), at(0.9).alias("p90"), F.round(F.max("ratio"), 6).alias("most"), F.round(F.corr("n", "optimal"), 6).alias("corr"), F.round(F.stddev("ratio"), 6).alias("spread"))


add("gap_spread_events", _gap_spread, f"{_gap_sql('events')} select round(quantile_cont(greedy / optimal, 0.5), 6) as median, round(quantile_cont(greedy / optimal, 0.9), 6) as p90, round(max(greedy / optimal), 6) as most, round(corr(n, optimal), 6) as corr, round(stddev(greedy / optimal), 6) as spread from own")


def _family(s, d):
    strings = families.strings_of(tables.taxes(s, d))
    made = parsers.compare(strings, parsers=("greedy", "optimal"))
    return strings.select("seq_id").join(families.closed_forms(strings), "seq_id").join(made.drop("n"), "seq_id").withColumn("ratio", F.round(F.col("greedy") / F.col("optimal"), 6))


add("bad_family", _family)
_B = lambda x: f"(2 * length(bin({x} + 1)) - 1)"
_part = lambda k: f"({k} - 1) * ({k} + 2) // 2"
add(
    "bad_family_closed_forms", lambda s, d: families.closed_forms(families.strings_of(tables.months(s, d))).select("seq_id", F.col("n").cast("long").alias("n"), "greedy_phrases", "near_phrases", "greedy_bits", "near_bits"),
    f"""with l as {tables.MONTHS}, head as (select l, {_B(2)} + {_B(1)} + {_B(1)} + {_B('(l - 1)')} + {_B(3)} + {_B(1)} + {_B('((1 << l) - 1)')} + 3 as h from l),
far as (select l, sum({_B(f"(l + 1 + (1 << l) + {_part('k')})")} + {_B('(k + 1)')}) as b from (select l, unnest(range(1, l + 1)) as k from l) group by l),
near as (select l, sum({_B('k')} * 2 + 1 + {_B(1)}) as b from (select l, unnest(range(2, l + 1)) as k from l) group by l)
select l as seq_id, ((1 << l) + l + 1 + l * (l + 3) // 2)::bigint as n, (l + 5)::bigint as greedy_phrases, (2 * l + 5)::bigint as near_phrases, (h + far.b)::bigint as greedy_bits, (h + 2 + {_B(2)} + {_B(1)} + near.b)::bigint as near_bits from head join far using (l) join near using (l)""",
)
# Phrases are never empty; a plain explode has Spark make them for every line, to filter empty ones before the lines are distinct.
add("bad_family_near_copy_parse", lambda s, d: families.near_copy_parse(families.strings_of(tables.taxes(s, d, 3))).select("seq_id", F.explode_outer("phrases").alias("p")).groupBy("seq_id").agg(F.count("*").alias("phrases"), F.sum("p.len").alias("n"), F.max("p.dist").cast("long").alias("farthest")), f"select l as seq_id, (2 * l + 5)::bigint as phrases, ((1 << l) + l + 1 + l * (l + 3) // 2)::bigint as n, l::bigint as farthest from {tables.TAXES} where l >= 3")
add("bad_family_shape", lambda s, d: measures.family_gap(measures.gap(families.strings_of(tables.taxes(s, d, 3)))).select("seq_id", F.round("ratio", 6).alias("ratio"), F.round("normalised", 6).alias("normalised")))
add("block_work", lambda s, d: measures.work(parsers.run(tables.spread(tables.supplier_lines(s, d)), ("optimal_block",), phrases=False)))

# The dictionary that grows with the parse.


def _grown(name):
    def query(s, d):
        return lz78.run(tables.ALL[name](s, d), ("greedy",)).select("seq_id", F.explode("parse").alias("p")).select("seq_id", "p.start", "p.len", "p.id", F.coalesce(F.col("p.sym").cast("long"), F.lit(-1)).alias("sym"))

    return query


_GROWN = """with recursive sym as materialized ({sym}), seq as materialized (select seq_id, list(s order by i) as syms, count(*)::int as n from sym group by seq_id),
walk as (select seq_id, syms, n, 1 as i, 0 as k, 0 as start, 0 as len, 0 as id, null::bigint as next, [[]::bigint[]] as known from seq
union all select seq_id, syms, n, i + m + 1, k + 1, i, least(m + 1, n - i + 1), list_position(known, syms[i:i + m - 1]) - 1, case when i + m <= n then syms[i + m] end, case when i + m <= n then list_append(known, syms[i:i + m]) else known end
from (select *, list_max(list_transform(range(0, n - i + 2), lambda l: case when list_contains(known, syms[i:i + l - 1]) then l else 0 end)) as m from walk where i <= n))
select seq_id, start, len, id::int as id, coalesce(next, -1) as sym from walk where k > 0"""
for _name in ("events", "orders"):
    add(f"lz78_phrases_{_name}", _grown(_name), _GROWN.replace("{sym}", tables.SYM[_name]))
add("lz78_methods_events", lambda s, d: lz78.run(tables.events(s, d), ("greedy", "flexible", "optimal", "fewest", "greedy_walk")).groupBy("seq_id").pivot("method", ["greedy", "flexible", "optimal", "fewest", "greedy_walk"]).agg(F.first("bits").alias("bits"), F.first("phrases").alias("phrases")))
add("lz78_optimal_documents", lambda s, d: lz78.run(tables.documents(s, d), ("optimal",), detail=False).select("seq_id", "n", "phrases", "bits"))

# A fixed dictionary: the words of part names, over the letters of the names.


def _static(s, d):
    part = tables.read(s, d, "part")
    # a vocabulary of names: bounded by it, not by the rows
    words = [r["w"] for r in part.select(F.explode(F.split("p_name", " ")).alias("w")).distinct().orderBy("w").collect()]
    known = [tuple(map(ord, w)) for w in words if w]
    return parsers.run(sequences.from_text(part, "p_partkey", "p_name"), ("static",), "gamma", "gamma", dictionary=known, phrases=False).select("seq_id", "bits")


add(
    "static_dict_optimal", _static,
    f"""with recursive words as (select w, row_number() over (order by w) as id from (select distinct unnest(string_split(p_name, ' ')) as w from part) where w <> ''),
pos as (select p_partkey::bigint as seq_id, p_name, unnest(range(1, length(p_name) + 1))::int as i from part),
edges as materialized (select seq_id, i, i + 1 as j, (1 + {_B('unicode(substr(p_name, i, 1))')})::bigint as bits from pos union all select seq_id, i, i + length(w)::int, {_B('id')}::bigint from pos join words on substr(p_name, i, length(w)) = w),
{tables.optimum_sql()} select seq_id, bits from best""",
)

# Entropies, sizes and round trips.
for _name in ("events", "documents", "benchmark"):
    for _k in (0, 1, 2):
        _context = f"list(s) over (partition by seq_id order by i rows between {_k} preceding and 1 preceding)" if _k else "[]"
        add(
            f"entropy_h{_k}_{_name}", lambda s, d, n=_name, k=_k: measures.entropy(tables.ALL[n](s, d), k).select("seq_id", "n", F.round("h", 6).alias("h")),
            f"with sym as ({tables.SYM[_name]}), pairs as (select seq_id, i, s, {_context} as c from sym), each as (select seq_id, c, s, count(*) as m from pairs where i > {_k} group by seq_id, c, s), t as (select *, sum(m) over (partition by seq_id, c) as total from each) select seq_id, sum(m)::bigint as n, round(sum(-m * log2(m / total)) / sum(m), 6) as h from t group by seq_id",
        )
add("redundancy_documents", lambda s, d: measures.redundancy(parsers.run(tables.documents(s, d), ("optimal",), phrases=False), tables.documents(s, d), 2))
add("ratio_documents", lambda s, d: measures.ratio(parsers.run(tables.documents(s, d), ("optimal",), phrases=False), tables.documents(s, d)))
add("codec_reference", lambda s, d: measures.codec(tables.read(s, d, "documents"), "doc_id", "text"))
add("bwt_reference", lambda s, d: measures.bwt_runs(tables.benchmark(s, d)))


def _roundtrip(name, table, key, text, unit):
    def query(s, d):
        parse = parsers.optimal(sequences.from_text(tables.spread(tables.read(s, d, table).select(key, text)), key, text, unit), "delta", "delta")
        back = sequences.to_text(bits.decode(bits.encode(parse)))
        return back.select("seq_id", F.md5(F.col("text").cast("binary")).alias("digest"))

    add(name, query, f"select {key}::bigint as seq_id, md5({text}) as digest from {table}")


_roundtrip("roundtrip_documents", "documents", "doc_id", "text", "codepoint")
_roundtrip("roundtrip_pages", "pages", "page_id", "html", "codepoint")
add("roundtrip_bits_events", lambda s, d: measures.roundtrip(parsers.run(tables.events(s, d), ("optimal",)), tables.events(s, d)).select("seq_id", "nbits", "same"), optimum("events")[1].replace("select seq_id, bits from best", "select seq_id, bits as nbits, true as same from best"))


def _by_source(s, d):
    docs, labels = tables.read(s, d, "documents"), tables.read(s, d, "labels")
    size = totals("documents")(s, d).withColumnRenamed("seq_id", "doc_id")
    own = docs.select("doc_id", "lang", "source").join(size, "doc_id").join(labels, "doc_id", "left")
    return own.rollup("lang", "source", "quality").agg(F.count("*").alias("docs"), F.sum("n").alias("n"), F.sum("bits").alias("bits"), F.round(F.sum("bits") / F.sum("n"), 6).alias("per_symbol"))


add("compressed_size_by_source", _by_source)
add("chunk_seam_penalty", lambda s, d: chunks.seams(tables.documents(s, d), 512, 1024, whole=True).withColumn("within", F.col("bits") <= F.col("whole") + F.col("allowance")))


def _frontier(s, d):
    """The optimum by chunks: copies may reach back over, and be as long as, the longest sequence."""
    seq = tables.events(s, d)
    longest = seq.agg(F.max("n")).first()[0] or 1
    chunk = max(16, -(-longest // 8))  # each chunk holds all before it: few chunks, so that this stays linear
    return chunks.exact(seq, chunk, longest, longest).select("seq_id", "bits")


for _w in (16, 64):  # the same in parts of few symbols, on line: what is final is given out after each
    add(f"online_optimum_w{_w}", lambda s, d, w=_w: chunks.online(chunks.split(tables.events(s, d), 10, 0), w, 1 << 20).groupBy("seq_id").agg(F.sum("bits").alias("bits")), optimum("events", window=_w)[1])
add("chunk_frontier_exact", _frontier, optimum("events")[1])
