"""Named queries over the given tables, with their SQL. Methods and measures here, relational operators in plans.relational."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Window, functions as F

from filterfleet.functions.frames import checkpointed, numbered, stored, table
from filterfleet.functions.hashing import positions, set_bits
from filterfleet.functions.params import FilterSpec, derive_k, expected_fp_column
from filterfleet.operators import distance, filters, grow, pack, scan, tree
from filterfleet.plans import costs, oracles as O, provenance
from filterfleet.sources.collections import collection, probes, string_key, tokens
from filterfleet.streaming import feeds

SPEC = FilterSpec(1500)
LINEAR = FilterSpec(1500, family="linear_odd")
DENSE = FilterSpec(600)
SMALL = FilterSpec(200)
WIDE_FLEET = FilterSpec(10_000)
D = 2

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(fn):
        QUERIES[fn.__name__] = fn
        if sql:
            ORACLES[fn.__name__] = sql
        return fn

    return add


def rounded(column: str, digits: int = 9):
    return F.round(column, digits).alias(column)


# --- filters ---------------------------------------------------------------------------------------------------------

TARGETS = [1e-7, 1e-5, 1e-3, 0.01, 0.1]


@query("select p, n, k, ceil(ceil(k / ln(2) * n) / 64)::bigint * 64 as m from (select p, n, ceil(-ln(p) / ln(2) - 1e-12)::bigint as k from (select unnest([1e-7, 1e-5, 1e-3, 0.01, 0.1]::double[]) as p), (select distinct n from (select count(distinct l_partkey) as n from lineitem group by l_suppkey)))")
def filter_params(spark, sf_dir):
    """Hash functions and bits for each target and each size that a supplier's set of parts has."""
    sizes = collection(spark, sf_dir, "supp").groupBy("site_id").agg(F.count("element").alias("n")).select("n").distinct()
    targets = F.explode(F.array(*(F.struct(F.lit(p).alias("p"), F.lit(derive_k(p)).cast("bigint").alias("k")) for p in TARGETS)))
    return sizes.select(targets.alias("of"), "n").select("of.p", "n", "of.k", (F.ceil(F.ceil(F.col("of.k") / F.log(F.lit(2.0)) * F.col("n")) / 64) * 64).cast("bigint").alias("m"))


def _set_sizes(spark, sf_dir):
    """(n): the sizes that suppliers' sets of parts have."""
    return collection(spark, sf_dir, "supp").groupBy("site_id").agg(F.count("element").alias("n")).select("n").distinct()


_SET_SIZES = "(select distinct n from (select count(distinct l_partkey) as n from lineitem group by l_suppkey))"


@query(f"select m, n, round(pow(1 - exp(-7.0::double * n / m), 7), 9) as fp from (select unnest(range(640, 25601, 640)) as m), {_SET_SIZES}")
def fp_curve_by_size(spark, sf_dir):
    """Analytic false-positive rate for each filter size, at each size that a supplier's set of parts has."""
    lengths = F.explode(F.sequence(F.lit(640).cast("bigint"), F.lit(25_600).cast("bigint"), F.lit(640).cast("bigint")))
    return _set_sizes(spark, sf_dir).select(lengths.alias("m"), "n").select("m", "n", F.round(expected_fp_column("n", "m", 7), 9).alias("fp"))


def _positions(spec):
    def run(spark, sf_dir):
        return collection(spark, sf_dir, "cust").select("element").distinct().select("element", F.posexplode(positions(F.col("element"), spec)).alias("i", "pos"))

    return run


QUERIES["hash_positions_linear"] = _positions(LINEAR)
ORACLES["hash_positions_linear"] = f"with e as (select distinct o_orderkey as element from orders), s as (select unnest({[a % LINEAR.m for a in LINEAR.seeds]}::bigint[]) as a, unnest(range({LINEAR.k})) as i) select element, i, (a * (element % {LINEAR.m})) % {LINEAR.m} as pos from e, s"
QUERIES["hash_positions_md5"] = _positions(SPEC)
ORACLES["hash_positions_md5"] = f"with e as (select distinct o_orderkey as element from orders) select element, i, (('0x' || substr(md5(element::varchar), 1, 15))::bigint % {SPEC.m} + i * (('0x' || substr(md5(element::varchar), 17, 15))::bigint % {SPEC.m})) % {SPEC.m} as pos from e, (select unnest(range({SPEC.k})) as i)"


@query(O.chain(O.members("cust"), O.bits(SPEC), O.words(), then="select filter_id, word_ix, word from words"))
def build_filter_words(spark, sf_dir):
    return filters.build_filters(collection(spark, sf_dir, "cust"), SPEC)


@query(O.chain(O.members("part"), O.bits(SPEC), then=f"select filter_id, count(*) as ones, round(count(*) / {SPEC.m}, 9) as fill, round(pow(count(*) / {SPEC.m}, {SPEC.k}), 9) as fp, count(*) = {SPEC.m} as saturated from bits group by filter_id"))
def filter_popcount_fill(spark, sf_dir):
    return filters.fill_stats(filters.build_filters(collection(spark, sf_dir, "part"), SPEC), SPEC, "filter_id").select("filter_id", "ones", rounded("fill"), rounded("fp"), "saturated")


@query(O.chain(O.members("cust"), O.bits(SPEC), O.words(), then="select word_ix, bit_or(word) as word from words group by word_ix"))
def root_union_words(spark, sf_dir):
    return filters.union_filters(filters.build_filters(collection(spark, sf_dir, "cust"), SPEC))


@query(O.chain(O.members("nation"), O.bits(SMALL), then="select r_name, count(distinct pos) as ones from bits join nation on n_nationkey = filter_id join region on r_regionkey = n_regionkey group by r_name"))
def region_union_filters(spark, sf_dir):
    words = filters.build_filters(collection(spark, sf_dir, "nation"), SMALL)
    places = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.expr("n_regionkey = r_regionkey")).select(F.col("n_nationkey").cast("bigint").alias("filter_id"), "r_name")
    return filters.fill_stats(filters.union_filters(words.join(places, "filter_id"), "r_name"), SMALL, "r_name").select("r_name", "ones")


def _report(spec):
    def run(spark, sf_dir):
        return filters.fill_report(collection(spark, sf_dir, "cust"), spec).select("n", "ones", *(rounded(c) for c in ("fill", "analytic_fill", "analytic_fp")))

    return run


for _name, _spec in (("fill_report_md5", SPEC), ("fill_report_linear", LINEAR)):
    QUERIES[_name] = _report(_spec)
    ORACLES[_name] = O.chain(O.members("cust"), O.bits(_spec), then=f"select n, ones, round(ones / {_spec.m}, 9) as fill, round(1 - exp(-{_spec.k}.0::double * n / {_spec.m}), 9) as analytic_fill, round(pow(1 - exp(-{_spec.k}.0::double * n / {_spec.m}), {_spec.k}), 9) as analytic_fp from (select count(distinct element) as n from mem), (select count(distinct pos) as ones from bits)")


@query(O.chain(O.members("user"), O.bits(SPEC), then=f"select filter_id, ones, round(-ln(1 - ones / {SPEC.m}) * {SPEC.m} / {SPEC.k}, 6) as estimate from (select filter_id, count(*) as ones from bits group by filter_id)"))
def cardinality_from_fill(spark, sf_dir):
    return filters.cardinality(filters.build_filters(collection(spark, sf_dir, "user"), SPEC), SPEC, "filter_id").select("filter_id", "ones", rounded("estimate", 6))


# --- scan ------------------------------------------------------------------------------------------------------------


def _scan(name, spec, every=100, dense=True):
    def run(spark, sf_dir):
        sets = collection(spark, sf_dir, name)
        if dense:
            return scan.scan_search(filters.to_dense(filters.build_filters(sets, spec), spec), probes(sets, every), spec)
        bits = set_bits(sets, spec).select(F.col("site_id").alias("filter_id"), "pos").distinct()
        return scan.scan_search_positions(bits, probes(sets, every), spec)

    return run


def _search_sql(name, spec, every=100, where=""):
    return O.chain(*O.search(name, spec, every, where), then="select query_id, filter_id from matches")


for _query, _name, _spec, _dense in (("scan_search_block", "block100", SPEC, True), ("scan_search_part", "part", SPEC, False), ("scan_search_supp", "supp", DENSE, False), ("scan_search_source", "source", SMALL, True)):
    QUERIES[_query], ORACLES[_query] = _scan(_name, _spec, dense=_dense), _search_sql(_name, _spec)


@query(_search_sql("cust", SPEC))
def scan_search_early_exit(spark, sf_dir):
    sets = collection(spark, sf_dir, "cust")
    return scan.scan_search_ordered(sets, probes(sets), SPEC)


@query(O.chain(*O.search("supp", DENSE), then="select query_id, element from probes where not exists (select 1 from matches m where m.query_id = probes.query_id)"))
def scan_negatives(spark, sf_dir):
    sets = collection(spark, sf_dir, "supp")
    return probes(sets).join(_scan("supp", DENSE, dense=False)(spark, sf_dir), "query_id", "left_anti").select("query_id", "element")


@query(O.chain(*O.search("supp", DENSE), then="select p.kind, count(*) as n_false from matches m join probes p using (query_id) where not exists (select 1 from mem where mem.site_id = m.filter_id and mem.element = p.element) group by p.kind"))
def scan_false_positives(spark, sf_dir):
    sets = checkpointed(collection(spark, sf_dir, "supp"))
    asked = probes(sets)
    found = _scan("supp", DENSE, dense=False)(spark, sf_dir).join(scan.exact_search(sets, asked), ["query_id", "filter_id"], "left_anti")
    return found.join(asked, "query_id").groupBy("kind").agg(F.count("*").alias("n_false"))


@query(O.chain(O.members("part"), O.probes(), then="select query_id, site_id as filter_id from probes join mem using (element)"))
def exact_membership(spark, sf_dir):
    sets = collection(spark, sf_dir, "part")
    return scan.exact_search(sets, probes(sets))


@query(O.chain(*O.search("supp", DENSE), ("truth", "select query_id, site_id as filter_id from probes join mem using (element)"), then="select tp, fp, fn, round(tp / (tp + fp), 9) as precision, round(tp / (tp + fn), 9) as recall from (select count(*) filter (where m.query_id is not null and t.query_id is not null) as tp, count(*) filter (where t.query_id is null) as fp, count(*) filter (where m.query_id is null) as fn from matches m full join truth t on m.query_id = t.query_id and m.filter_id = t.filter_id)"))
def result_accuracy(spark, sf_dir):
    sets = checkpointed(collection(spark, sf_dir, "supp"))
    found = _scan("supp", DENSE, dense=False)(spark, sf_dir)
    return filters.accuracy(found, scan.exact_search(sets, probes(sets))).select("tp", "fp", "fn", rounded("precision"), rounded("recall"))


@query(O.chain(O.members("cust"), O.probes(), then="select query_id, (select count(distinct site_id) from mem) as nodes_checked from probes"))
def scan_cost(spark, sf_dir):
    sets = collection(spark, sf_dir, "cust")
    return scan.scan_cost(sets.select(F.col("site_id").alias("filter_id")), probes(sets))


# --- distances -------------------------------------------------------------------------------------------------------

PAIRS = [("ones", "select filter_id, count(*)::bigint as n from bits group by filter_id"), ("shared", "select a.filter_id as a, b.filter_id as b, count(*)::bigint as c from bits a join bits b on a.pos = b.pos and a.filter_id <> b.filter_id group by 1, 2"), ("pairs", "select x.filter_id as a, y.filter_id as b, x.n as na, y.n as nb, coalesce(c, 0) as c from ones x join ones y on x.filter_id <> y.filter_id left join shared on shared.a = x.filter_id and shared.b = y.filter_id")]
FORMULA = {"hamming": "(na + nb - 2 * c)::double", "jaccard": "round(1 - c / (na + nb - c), 9)", "cosine": "round(1 - c / (sqrt(na::double) * sqrt(nb::double)), 9)"}


def _pairs(metric):
    def run(spark, sf_dir):
        words = filters.build_filters(collection(spark, sf_dir, "supp"), DENSE)
        return distance.all_pairs(words, words, metric).select("a", "b", rounded(metric))

    return run


for _metric in distance.METRICS:
    QUERIES[f"{_metric}_pairs"] = _pairs(_metric)
    ORACLES[f"{_metric}_pairs"] = O.chain(O.members("supp"), O.bits(DENSE), *PAIRS, then=f"select a, b, {FORMULA[_metric]} as {_metric} from pairs where a < b")


@query(O.chain(O.members("supp"), O.bits(DENSE), *PAIRS, then="select a as filter_id, arg_min(b, {'d': na + nb - 2 * c, 'b': b}) as neighbour, min(na + nb - 2 * c)::double as distance from pairs group by a"))
def nearest_filter(spark, sf_dir):
    return distance.nearest(filters.build_filters(collection(spark, sf_dir, "supp"), DENSE))


@query("with s as (select label, vec_id, list_reduce(list_transform(range(64), lambda i: case when embedding[i + 1] > 0 then case when i = 63 then (-9223372036854775808)::bigint else 1::bigint << i::int end else 0::bigint end), lambda x, y: x | y) as w from embeddings), u as (select label, bit_or(w) as word from s group by label) select a.label as a, b.label as b, bit_count(xor(a.word, b.word))::bigint as hamming from u a join u b on a.label < b.label")
def embedding_sign_hamming(spark, sf_dir):
    bit = lambda x, i: F.when(x > 0, F.call_function("shiftleft", F.lit(1).cast("bigint"), i)).otherwise(F.lit(0).cast("bigint"))
    signs = F.aggregate(F.transform("embedding", bit), F.lit(0).cast("bigint"), lambda a, b: a.bitwiseOR(b))
    words = table(spark, sf_dir, "embeddings").select("label", signs.alias("w")).groupBy("label").agg(F.bit_or("w").alias("word"))
    a, b = words.select(F.col("label").alias("a"), F.col("word").alias("x")), words.select(F.col("label").alias("b"), F.col("word").alias("y"))
    return a.join(b, F.expr("a < b")).select("a", "b", F.bit_count(F.col("x").bitwiseXOR(F.col("y"))).cast("bigint").alias("hamming"))


# --- tree ------------------------------------------------------------------------------------------------------------


def _bulk(spark, sf_dir, name="cust", spec=SPEC, d=D, order="id"):
    words = filters.build_filters(collection(spark, sf_dir, name), spec)
    return tree.bulk_load(words, spec, d, order)


@query(O.chain(O.members("cust"), *O.sizes(D), O.edges(D), then="select node_id, parent_id, level, n_children::int as n_children from shape"))
def bulk_topology(spark, sf_dir):
    return _bulk(spark, sf_dir).nodes.select("node_id", "parent_id", "level", "n_children")


@query(O.chain(O.members("cust"), O.bits(SPEC), *O.sizes(D), O.NODE_BITS, then="select node_id, count(*) as ones from nbits join nodes using (level, ix) group by node_id"))
def bulk_node_popcounts(spark, sf_dir):
    return _bulk(spark, sf_dir).words.groupBy("node_id").agg(F.sum(F.bit_count("word")).alias("ones"))


def _tree_search(name, spec, d=D, order="id"):
    def run(spark, sf_dir):
        return tree.tree_search(_bulk(spark, sf_dir, name, spec, d, order), probes(collection(spark, sf_dir, name)))[0]

    return run


QUERIES["tree_search_bulk"], ORACLES["tree_search_bulk"] = _tree_search("cust", SPEC), _search_sql("cust", SPEC)
QUERIES["tree_search_overlap"], ORACLES["tree_search_overlap"] = _tree_search("part", SPEC, 4), _search_sql("part", SPEC)
QUERIES["tree_search_by_ones"], ORACLES["tree_search_by_ones"] = _tree_search("supp", DENSE, 3, "ones"), _search_sql("supp", DENSE)
QUERIES["tree_search_by_minhash"], ORACLES["tree_search_by_minhash"] = _tree_search("user", SPEC, 2, "minhash"), _search_sql("user", SPEC)

_COST = [*O.search("cust", WIDE_FLEET), *O.sizes(D), O.NODE_BITS, O.NODE_HITS, O.edges(D)]


@query(O.chain(*_COST, then="select p.query_id, 1 + coalesce(sum(n_children), 0)::bigint as nodes_checked from probes p left join hits h on h.query_id = p.query_id and h.level > 0 left join shape s on s.level = h.level and s.ix = h.ix group by p.query_id"))
def tree_bf_cost_bulk(spark, sf_dir):
    index = _bulk(spark, sf_dir, "cust", WIDE_FLEET)
    return tree.search_cost(tree.tree_search(index, probes(collection(spark, sf_dir, "cust")))[1])


@query(ORACLES["tree_bf_cost_bulk"])
def tree_counted_cost(spark, sf_dir):
    return tree.counted_cost(_bulk(spark, sf_dir, "cust", WIDE_FLEET), probes(collection(spark, sf_dir, "cust")))


@query(O.chain(*_COST, then="select level, count(*) as checked, count(*) filter (where hit) as matched, round(1 - count(*) filter (where hit) / count(*), 9) as pruned from (select c.query_id, c.level, h.query_id is not null as hit from (select p.query_id, s.level, s.ix from probes p, shape s where s.parent_id is null union all select h.query_id, s.level, s.ix from hits h join nodes n on n.level = h.level and n.ix = h.ix join shape s on s.parent_id = n.node_id where h.level > 0) c left join hits h on h.query_id = c.query_id and h.level = c.level and h.ix = c.ix) group by level"))
def pruning_by_level(spark, sf_dir):
    index = _bulk(spark, sf_dir, "cust", WIDE_FLEET)
    return costs.pruning_by_level(tree.tree_search(index, probes(collection(spark, sf_dir, "cust")))[1]).select("level", "checked", "matched", rounded("pruned"))


@query(O.chain(O.members("cust"), O.bits(SPEC), *O.sizes(D), O.NODE_BITS, then=f"select level, n_nodes, round(s / n_nodes, 9) as mean_fill from (select lv.level, any_value(lv.n) as n_nodes, sum(f) as s from lv join (select level, ix, count(*) / {SPEC.m} as f from nbits group by level, ix) x on x.level = lv.level group by lv.level)"))
def level_fill(spark, sf_dir):
    return tree.level_fill(_bulk(spark, sf_dir)).select("level", "n_nodes", rounded("mean_fill"))


@query(O.chain(O.members("cust"), O.bits(SPEC), O.probes(), O.probe_bits(SPEC), then="select query_id from pb join (select distinct pos from bits) using (pos) group by query_id having count(*) = any_value(kd)"))
def any_membership(spark, sf_dir):
    return tree.any_match(_bulk(spark, sf_dir), probes(collection(spark, sf_dir, "cust")))


@query(ORACLES["any_membership"])
def one_filter_test(spark, sf_dir):
    """The filter of all sites together, dense, asked by each probe."""
    sets = collection(spark, sf_dir, "cust")
    whole = filters.union_filters(filters.build_filters(sets, SPEC).withColumn("filter_id", F.lit(0)), "filter_id")
    dense = F.broadcast(filters.to_dense(whole, SPEC).select("words"))  # one row
    return probes(sets).join(dense, filters.matches_expr(F.col("words"), F.col("element"), SPEC)).select("query_id")


@query(O.chain(*O.search("cust", SPEC), then="select m.query_id, m.filter_id from matches m where m.filter_id = (m.query_id * 7) % 1000"))
def site_membership(spark, sf_dir):
    asked = probes(collection(spark, sf_dir, "cust")).withColumn("filter_id", F.expr("(query_id * 7) % 1000"))
    return tree.site_match(_bulk(spark, sf_dir), asked)


def _greedy(metric="hamming", spec=SMALL, name="nation", **options):
    def run(spark, sf_dir):
        sets = collection(spark, sf_dir, name)
        index = grow.grow(filters.build_filters(sets, spec), spec, D, metric, **options)
        return tree.tree_search(index, probes(sets, 10))[0]

    return run


for _metric in distance.METRICS:
    QUERIES[f"tree_search_greedy_{_metric}"] = _greedy(_metric, SPEC, "cust" if _metric == "hamming" else "user")
    ORACLES[f"tree_search_greedy_{_metric}"] = _search_sql("cust" if _metric == "hamming" else "user", SPEC, 10)
QUERIES["tree_search_chain"], ORACLES["tree_search_chain"] = _greedy("jaccard", DENSE, "supp", method="chain"), _search_sql("supp", DENSE, 10)
QUERIES["tree_search_forest"], ORACLES["tree_search_forest"] = _greedy("hamming", SPEC, "part", shards=8), _search_sql("part", SPEC, 10)
QUERIES["tree_saturation_rule"], ORACLES["tree_saturation_rule"] = _greedy("hamming", SMALL, "part", saturation_rule=True), _search_sql("part", SMALL, 10)


@query(O.chain(*O.search("user", SPEC, 10, "where filter_id % 10 <> 0"), then="select query_id, filter_id from matches"))
def tree_delete_then_search(spark, sf_dir):
    sets = collection(spark, sf_dir, "user")
    words = filters.build_filters(sets, SPEC)
    index = grow.grow(words, SPEC, D, deletes=words.where("filter_id % 10 = 0").select("filter_id").distinct())
    return tree.tree_search(index, probes(sets, 10))[0]


@query(ORACLES["bulk_node_popcounts"])
def tree_update_inplace(spark, sf_dir):
    sets = collection(spark, sf_dir, "cust")
    places = numbered(sets.select(F.col("site_id").alias("filter_id")).distinct(), "filter_id", "place")
    half = tree.bulk_load(filters.build_filters(sets.where("element % 2 = 0"), SPEC), SPEC, D, places=places)
    full = tree.tree_update(half, filters.build_filters(sets.where("element % 2 = 1"), SPEC))
    return full.words.groupBy("node_id").agg(F.sum(F.bit_count("word")).alias("ones"))


@query(O.chain(O.members("cust"), *O.sizes(D), then=f"select max(level) as height, count(*) as n_nodes, count(*) * {SPEC.m} // 8 as tree_bytes, (select n from lv where level = 0) * {SPEC.m} // 8 as scan_bytes, ((select n from lv where level = 0) + 63) // 64 * 64 * {SPEC.m} // 8 as pack_bytes from nodes"))
def storage_by_method(spark, sf_dir):
    made = tree.shape(_bulk(spark, sf_dir)).select("height", "n_nodes", (F.col("n_nodes") - F.col("n_inner")).alias("n"))
    size = lambda c: F.expr(f"({c}) * {SPEC.m} div 8")
    return made.select("height", "n_nodes", size("n_nodes").alias("tree_bytes"), size("n").alias("scan_bytes"), size("(n + 63) div 64 * 64").alias("pack_bytes"))


@query(f"select n, l, round(l * ln(n) / ln(l) + 1, 6) as cost from {_SET_SIZES}, (select unnest([2, 3, 4, 10]::bigint[]) as l)")
def ideal_cost_curve(spark, sf_dir):
    """Nodes tested along one path of a tree over as many filters as a supplier has parts."""
    cost = F.udf(lambda n, l: float(tree.ideal_cost(n, l)), "double")  # noqa: E741
    fanouts = F.explode(F.array(*(F.lit(k).cast("bigint") for k in (2, 3, 4, 10))))
    return _set_sizes(spark, sf_dir).select("n", fanouts.alias("l")).select("n", "l", F.round(cost("n", "l"), 6).alias("cost"))


@query("select 'sound' as verdict, 0::bigint as n_broken")
def tree_violations(spark, sf_dir):
    sets = collection(spark, sf_dir, "user")
    broken = tree.violations(_bulk(spark, sf_dir)).unionByName(tree.violations(grow.grow(filters.build_filters(sets, SPEC), SPEC, 3)))
    return broken.agg(F.lit("sound").alias("verdict"), F.count("*").alias("n_broken"))


# --- pack ------------------------------------------------------------------------------------------------------------

_SLOTS = ("slots", "select filter_id, row_number() over (order by filter_id) - 1 as slot from (select distinct site_id as filter_id from mem)")
_WORDS = "select slot // 64 as block_id, pos, bit_or(" + O.BIT.format(p="slot") + ") as word from bits join slots using (filter_id) group by 1, 2"


@query(O.chain(O.members("cust"), O.bits(SPEC), _SLOTS, then=_WORDS))
def pack_words(spark, sf_dir):
    return pack.pack_build(collection(spark, sf_dir, "cust"), SPEC).slices


def _pack(name, spec, how):
    def run(spark, sf_dir):
        sets = collection(spark, sf_dir, name)
        index = pack.pack_build(sets, spec)
        if how == "wide":
            return pack.wide_search(pack.to_wide(index), index, probes(sets))
        return (pack.hybrid_search if how == "hybrid" else pack.pack_search)(index, probes(sets))

    return run


for _query, _name, _spec, _how in (("pack_search", "cust", SPEC, ""), ("pack_search_overlap", "part", SPEC, ""), ("pack_search_fleet", "order", FilterSpec(2000), ""), ("pack_wide_search", "user", SPEC, "wide"), ("pack_hybrid_search", "part", SPEC, "hybrid"), ("pack_search_days", "day", SMALL, ""), ("pack_search_supnat", "supnat", SPEC, "")):
    QUERIES[_query], ORACLES[_query] = _pack(_name, _spec, _how), _search_sql(_name, _spec)


@query(O.chain(O.members("cust"), O.bits(SPEC), _SLOTS, O.probes(), O.probe_bits(SPEC), ("sl", "select distinct slot // 64 as block_id, pos from bits join slots using (filter_id)"), then="select p.query_id, count(sl.pos) as words_read from pb p left join sl using (pos) group by p.query_id"))
def pack_words_read(spark, sf_dir):
    sets = collection(spark, sf_dir, "cust")
    return pack.words_read(pack.pack_build(sets, SPEC), probes(sets))


_FREED = ("freed", "select slot, row_number() over (order by slot) - 1 as turn from slots where filter_id % 7 = 0")
_FRESH = ("fresh", "select site_id + 1000000 as filter_id, row_number() over (order by site_id) - 1 as turn from (select distinct site_id from mem where site_id % 5 = 0)")


@query(O.chain(O.members("cust"), _SLOTS, _FREED, _FRESH, then="select filter_id, slot from slots where filter_id % 7 <> 0 union all select fresh.filter_id, coalesce(freed.slot, fresh.turn - (select count(*) from freed) + ((select max(slot) from slots) // 64 + 1) * 64) as slot from fresh left join freed using (turn)"))
def pack_insert_reuse(spark, sf_dir):
    sets = collection(spark, sf_dir, "cust")
    index = pack.pack_delete(pack.pack_build(sets, SPEC), sets.where("site_id % 7 = 0").select(F.col("site_id").alias("filter_id")), compact=False)
    index = pack.pack_insert(index, sets.where("site_id % 5 = 0").withColumn("site_id", F.col("site_id") + 1_000_000))
    return index.slots.where("in_use").select("filter_id", "slot")


@query(O.chain(O.members("cust"), O.bits(SPEC), _SLOTS, then=_WORDS.replace("using (filter_id)", "using (filter_id) where filter_id % 7 <> 0")))
def pack_delete_clear(spark, sf_dir):
    sets = collection(spark, sf_dir, "cust")
    return pack.pack_delete(pack.pack_build(sets, SPEC), sets.where("site_id % 7 = 0").select(F.col("site_id").alias("filter_id")), compact=False).slices


@query(O.chain(O.members("cust"), _SLOTS, ("kept", "select block_id, row_number() over (order by block_id) - 1 as moved from (select distinct slot // 64 as block_id from slots where filter_id % 1000 >= 300)"), then="select filter_id, moved * 64 + slot % 64 as slot from slots join kept on kept.block_id = slot // 64 where filter_id % 1000 >= 300"))
def pack_delete_compact(spark, sf_dir):
    sets = collection(spark, sf_dir, "cust")
    gone = sets.where("site_id % 1000 < 300").select(F.col("site_id").alias("filter_id"))
    return pack.pack_delete(pack.pack_build(sets, SPEC), gone).slots.where("in_use").select("filter_id", "slot")


@query(ORACLES["pack_words"])
def pack_update(spark, sf_dir):
    sets = collection(spark, sf_dir, "cust")
    slots = pack.assign_slots(sets.select(F.col("site_id").alias("filter_id")))
    half = pack.pack_build(sets.where("element % 2 = 0"), SPEC, slots)
    return pack.pack_update(half, sets.where("element % 2 = 1")).slices


@query(O.chain(O.members("user"), then="select filter_id, row_number() over (order by filter_id) - 1 as slot from (select distinct site_id as filter_id from mem where site_id % 3 <> 0)"))
def pack_compact(spark, sf_dir):
    sets = collection(spark, sf_dir, "user")
    index = pack.pack_delete(pack.pack_build(sets, SPEC), sets.where("site_id % 3 = 0").select(F.col("site_id").alias("filter_id")), compact=False)
    return pack.pack_compact(index).slots.select("filter_id", "slot")


@query(O.chain(O.members("cust"), _SLOTS, then="select (slot // 64)::int as block_id, round(count(*) filter (where filter_id % 2 = 0) / 64, 6) as used from slots group by 1"))
def pack_fragmentation(spark, sf_dir):
    sets = collection(spark, sf_dir, "cust")
    index = pack.pack_delete(pack.pack_build(sets, SPEC), sets.where("site_id % 2 = 1").select(F.col("site_id").alias("filter_id")), compact=False)
    return pack.fragmentation(index).select("block_id", rounded("used", 6))


# --- applications ----------------------------------------------------------------------------------------------------


@query(O.chain(O.members("day"), O.bits(SMALL), O.words(), ("u", "select o.day, word_ix, bit_or(word) as word from words, (select distinct site_id as day from mem) o where filter_id between o.day - 6 and o.day group by o.day, word_ix"), then="select day, word_ix, word from u"))
def window_filters_7day(spark, sf_dir):
    return feeds.moving_window(filters.build_filters(collection(spark, sf_dir, "day"), SMALL).withColumnRenamed("filter_id", "day"), 7)


def _turns(spark, sf_dir):
    key = lambda turn: F.col("conv_id") * 1000 + turn
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn").distinct()
    edges = turns.where("turn > 0").select(F.pmod(F.col("conv_id") + F.col("turn"), F.lit(16)).alias("site_id"), key(F.col("turn")).alias("child"), key(F.col("turn") - 1).alias("parent"))
    return edges, turns.groupBy("conv_id").agg(F.max("turn").alias("turn")).select(key(F.col("turn")).alias("item"))


_TURNS = [("edges", "select distinct (conv_id + turn) % 16 as site_id, conv_id * 1000 + turn as child, conv_id * 1000 + turn - 1 as parent from conversations where turn > 0"), ("starts", "select max(conv_id * 1000 + turn) as item from conversations group by conv_id"), ("walk", "select item as start, item, 0 as round from starts union select walk.start, edges.parent, walk.round + 1 from walk join edges on edges.child = walk.item")]


@query(O.chain(*_TURNS, then="select start, item from walk where start <> item"))
def provenance_conversation(spark, sf_dir):
    return provenance.trace(*_turns(spark, sf_dir), SMALL)[0]


@query(O.chain(*_TURNS, ("mem", "select distinct site_id, child as element from edges"), O.bits(SMALL), ("probes", "select distinct item as query_id, item as element, round from walk"), ("pb", f"select query_id, round, pos, count(*) over (partition by query_id) as kd from (select distinct query_id, round, pos from ({O.positions('probes', 'query_id, round', SMALL)}))"), ("hit", "select query_id, any_value(round) as round, filter_id from pb join bits using (pos) group by query_id, filter_id having count(*) = any_value(kd)"), then="select p.round, (select count(*) from hit where hit.round = p.round) as with_index, count(*) * (select count(distinct site_id) from edges) as without_index from probes p group by p.round"))
def provenance_messages(spark, sf_dir):
    return costs.messages(provenance.trace(*_turns(spark, sf_dir), SMALL)[1])


@query(O.chain(O.members("source"), O.bits(SMALL), ("probes", "select distinct element as query_id, element from mem"), O.probe_bits(SMALL), O.matches(), then="select query_id, count(*) as n_sources from matches group by query_id"))
def source_copies_lookup(spark, sf_dir):
    sets = collection(spark, sf_dir, "source")
    asked = sets.select(F.col("element").alias("query_id"), "element").distinct()
    return pack.pack_search(pack.pack_build(sets, SMALL), asked).groupBy("query_id").agg(F.count("*").alias("n_sources"))


_BENCH = r"select distinct item_id, unnest(regexp_split_to_array(lower(text), '[^\p{L}0-9]+')) as w from benchmark"


@query(O.chain(O.members("doc"), O.bits(WIDE_FLEET), ("asked", f"select item_id, ('0x' || substr(md5(w), 1, 15))::bigint as element from ({_BENCH}) where w <> ''"), ("probes", "select distinct element as query_id, element from asked"), O.probe_bits(WIDE_FLEET), O.matches(), ("total", "select item_id, count(*) as n from asked group by item_id"), then="select item_id, filter_id, count(*) as shared from asked join matches on query_id = element join total using (item_id) group by item_id, filter_id, n having count(*) >= 0.9 * n"))
def benchmark_overlap_docs(spark, sf_dir):
    """Documents that may hold nine tenths of a benchmark item's words."""
    asked = table(spark, sf_dir, "benchmark").select("item_id", F.explode(tokens()).alias("w")).distinct().select("item_id", string_key(F.col("w")).alias("element"))
    asked = checkpointed(asked)
    index = pack.pack_build(collection(spark, sf_dir, "doc"), WIDE_FLEET)
    found = pack.pack_search(index, asked.select(F.col("element").alias("query_id"), "element").distinct())
    total = asked.groupBy("item_id").agg(F.count("*").alias("n"))
    shared = asked.join(found, F.col("query_id") == F.col("element")).groupBy("item_id", "filter_id").agg(F.count("*").alias("shared"))
    return shared.join(total, "item_id").where("shared >= 0.9 * n").select("item_id", "filter_id", "shared")


@query(O.chain(*O.search("user", SPEC), then="select count(*) as n_scan, count(*) as n_tree, count(*) as n_pack, 0::bigint as n_apart from matches"))
def method_agreement(spark, sf_dir):
    sets = collection(spark, sf_dir, "user")
    words = filters.build_filters(sets, SPEC)
    asked = checkpointed(probes(sets))
    found = {
        "scan": scan.scan_search(filters.to_dense(words, SPEC), asked, SPEC),
        "tree": tree.tree_search(grow.grow(words, SPEC, D), asked)[0],
        "pack": pack.pack_search(pack.pack_build(sets, SPEC), asked),
    }
    tagged = [d.select("query_id", "filter_id", F.lit(k).alias("method")) for k, d in found.items()]
    pairs = tagged[0].unionByName(tagged[1]).unionByName(tagged[2]).groupBy("query_id", "filter_id").agg(*(F.count_if(F.col("method") == k).alias(k) for k in found))
    total = lambda k: F.coalesce(F.sum(k), F.lit(0)).alias(f"n_{k}")
    return pairs.agg(*map(total, found), F.count_if(F.expr("scan <> 1 or tree <> 1 or pack <> 1")).alias("n_apart"))



# --- upkeep, replicas, rebuilds, measures, experiments ---------------------------------------------------------------


@query(ORACLES["tree_bf_cost_bulk"])
def tree_search_replicas(spark, sf_dir):
    found = tree.tree_search_local(_bulk(spark, sf_dir, "cust", WIDE_FLEET), probes(collection(spark, sf_dir, "cust")))
    return found.select("query_id", "nodes_checked").distinct()


@query(_search_sql("user", SPEC))
def tree_search_in_shards(spark, sf_dir):
    sets = collection(spark, sf_dir, "user")
    asked = probes(sets)
    spots = asked.select("query_id", positions(F.col("element"), SPEC).alias("spots"))
    return grow.shard_search(filters.build_filters(sets, SPEC), spots, SPEC, shards=4).select("query_id", F.explode("filter_ids").alias("filter_id"))


@query(_search_sql("cust", SPEC))
def tree_rebuild_search(spark, sf_dir):
    sets = collection(spark, sf_dir, "cust")
    grown = grow.grow(filters.build_filters(sets, SPEC), SPEC, D, shards=4)
    return tree.tree_search(tree.rebuild(grown, d=4), probes(sets))[0]


class _Resized:
    """The spec of the resized tree as SQL sees it: its length follows from the elements that are there."""

    family, k, m = "md5_double", SPEC.k, "(select m from wide)"


_WIDE = ("wide", f"select ceil(ceil({SPEC.k} / ln(2) * count(distinct element)) / 64)::bigint * 64 as m from mem")


@query(O.chain(O.members("user"), _WIDE, O.bits(_Resized), O.probes(), O.probe_bits(_Resized), O.matches(), then="select query_id, filter_id from matches"))
def tree_resize_search(spark, sf_dir):
    sets = collection(spark, sf_dir, "user")
    return tree.tree_search(tree.resize(sets, SPEC), probes(sets))[0]


@query(O.chain(("mem", "select site_id, element from (" + O.MEMBERS["cust"] + ") where site_id % 10 <> 0 or element % 2 = 0"), ("all_sites", "select distinct o_custkey as site_id from orders"), O.bits(SPEC), *O.sizes(D, "all_sites"), O.NODE_BITS, then="select node_id, count(*) as ones from nbits join nodes using (level, ix) group by node_id"))
def tree_replace_filters(spark, sf_dir):
    sets = collection(spark, sf_dir, "cust")
    changed = sets.where("site_id % 10 = 0").select(F.col("site_id").alias("filter_id")).distinct()
    fresh = filters.build_filters(sets.where("site_id % 10 <> 0 or element % 2 = 0"), SPEC)
    return tree.tree_replace(_bulk(spark, sf_dir), fresh, changed).words.groupBy("node_id").agg(F.sum(F.bit_count("word")).alias("ones"))


@query(O.chain(("mem", "select site_id, element from (" + O.MEMBERS["cust"] + ") where site_id % 5 <> 0"), O.bits(SPEC), then="select filter_id, count(*) as ones from bits group by filter_id"))
def scan_maintenance(spark, sf_dir):
    sets = collection(spark, sf_dir, "cust")
    old, fresh = sets.where("element % 3 <> 0 and site_id % 2 = 0"), sets.where("element % 3 <> 0 and site_id % 2 = 1")
    words = scan.scan_insert(filters.build_filters(old, SPEC), filters.build_filters(fresh, SPEC))
    words = scan.scan_update(words, filters.build_filters(sets.where("element % 3 = 0"), SPEC))
    words = scan.scan_delete(words, sets.where("site_id % 5 = 0").select(F.col("site_id").alias("filter_id")).distinct())
    return filters.fill_stats(words, SPEC, "filter_id").select("filter_id", "ones")


@query(O.chain(O.members("nation"), O.bits(SMALL), then="select filter_id, count(*) as ones from bits group by filter_id"))
def bitmap_layout(spark, sf_dir):
    return filters.to_bitmaps(collection(spark, sf_dir, "nation"), SMALL).groupBy("filter_id").agg(F.sum(F.bitmap_count("bitmap")).alias("ones"))


@query(O.chain(O.members("nation"), O.bits(SMALL), then="select filter_id, pos from bits"))
def filter_layouts(spark, sf_dir):
    words = filters.build_filters(collection(spark, sf_dir, "nation"), SMALL)
    return filters.to_positions(filters.to_sparse(filters.to_dense(words, SMALL)))


@query(O.chain(*_COST, ("c", "select p.query_id, 1 + coalesce(sum(n_children), 0) as n from probes p left join hits h on h.query_id = p.query_id and h.level > 0 left join shape s on s.level = h.level and s.ix = h.ix group by p.query_id"), ("w", "select count(*) as n from leaves"), then="select round(avg(c.n), 6) as bf_cost, round(any_value(3 * ln(w.n) / ln(3) + 1), 6) as ideal, round(avg(c.n) / any_value(3 * ln(w.n) / ln(3) + 1), 6) as ratio, avg(c.n) / any_value(3 * ln(w.n) / ln(3) + 1) > 3 as rebuild from c, w"))
def decay_report(spark, sf_dir):
    sets = collection(spark, sf_dir, "cust")
    n = sets.select("site_id").distinct().count()
    made = costs.decay_report(tree.tree_search(_bulk(spark, sf_dir, "cust", WIDE_FLEET), probes(sets))[1], n, D + 1)
    return made.select(*(rounded(c, 6) for c in ("bf_cost", "ideal", "ratio")), "rebuild")


# --- measures by themselves -------------------------------------------------------------------------------------------


@query(O.chain(*O.search("part", SPEC), then="select round((select count(*) from matches) / (select count(*) from probes), 9) as mean_matches"))
def mean_matches(spark, sf_dir):
    sets = collection(spark, sf_dir, "part")
    asked = checkpointed(probes(sets))
    return costs.mean_matches(pack.pack_search(pack.pack_build(sets, SPEC), asked), asked.count()).select(rounded("mean_matches"))


_PER_PROBE = ("c", "select p.query_id, 1 + coalesce(sum(n_children), 0) as n from probes p left join hits h on h.query_id = p.query_id and h.level > 0 left join shape s on s.level = h.level and s.ix = h.ix group by p.query_id")


@query(O.chain(*_COST, _PER_PROBE, ("w", "select count(*) as n from leaves"), then="select round(avg(c.n), 6) as bf_cost, round(avg(c.n) - any_value(3 * ln(w.n) / ln(3) + 1), 6) as gap from c, w"))
def gap_to_ideal(spark, sf_dir):
    sets = collection(spark, sf_dir, "cust")
    found = tree.tree_search(_bulk(spark, sf_dir, "cust", WIDE_FLEET), probes(sets))[1]
    return costs.gap_to_ideal(found, sets.select("site_id").distinct().count(), D + 1).select(rounded("bf_cost", 6), rounded("gap", 6))


@query(O.chain(O.members("cust"), O.bits(SPEC), *O.sizes(D), O.NODE_BITS, then=f"select lv.level, any_value(lv.n) as n_nodes, round(sum(fp) / any_value(lv.n), 9) as mean_fp, (select round(pow(1 - exp(-{SPEC.k}.0::double * count(distinct element) / {SPEC.m}), {SPEC.k}), 9) from mem) as root_analytic from lv join (select level, ix, pow(count(*) / {SPEC.m}, {SPEC.k}) as fp from nbits group by level, ix) x on x.level = lv.level group by lv.level"))
def level_fp(spark, sf_dir):
    elements = collection(spark, sf_dir, "cust").select("element").distinct().count()
    return costs.level_fp(_bulk(spark, sf_dir), elements).select("level", "n_nodes", rounded("mean_fp"), rounded("root_analytic"))


@query(O.chain(O.members("user"), *O.sizes(D), then="select filter_id, (select max(level) + 1 from lv) as accessed from leaves where filter_id % 10 = 0"))
def update_bf_cost(spark, sf_dir):
    """Nodes that an update of each tenth filter writes: its leaf and all above."""
    index = _bulk(spark, sf_dir, "user")
    return tree.ancestors(index.nodes).where("filter_id % 10 = 0").groupBy("filter_id").agg(F.count("*").alias("accessed"))


def maintenance_bf_cost(spark, sf_dir):
    """Mean nodes that an insertion reads or writes, by distance measure; greedy growth has no SQL form."""
    words = checkpointed(filters.build_filters(collection(spark, sf_dir, "user"), SPEC))
    made = [costs.maintenance_bf_cost(grow.grow(words, SPEC, D, metric).accessed).select(F.lit(metric).alias("metric"), "bf_cost") for metric in distance.METRICS]
    return made[0].unionByName(made[1]).unionByName(made[2])


QUERIES["maintenance_bf_cost"] = maintenance_bf_cost

_BOUNDS = """
with recursive given as (select n, d from (select distinct n from (select count(distinct l_partkey) as n from lineitem group by l_suppkey)), (select unnest([2, 3, 4, 10]::bigint[]) as d)),
lv as (select n, d, 0 as level, n as here from given
       union all select n, d, level + 1, case when here <= 2 * d then 1 else (here - d) // (d + 1) + 1 end from lv where here > 1 or level = 0)
select n, d, max(level)::bigint as height, any_value(case when n <= 2 * d then 1 else 1 + floor(ln(n / 2.0) / ln(d) + 1e-9) end)::bigint as bound, sum(here)::bigint as n_nodes from lv group by n, d
"""


@query(_BOUNDS)
def tree_height_bounds(spark, sf_dir):
    """Height and nodes of sorted loads of as many filters as a supplier has parts, beside the bound on the height."""

    def measures(n, d):
        sizes = tree.level_sizes(n, d)
        return len(sizes) - 1, tree.height_bound(n, d), sum(sizes)

    orders = F.explode(F.array(*(F.lit(d).cast("bigint") for d in (2, 3, 4, 10))))
    of = F.udf(measures, "height long, bound long, n_nodes long")
    return _set_sizes(spark, sf_dir).select("n", orders.alias("d")).select("n", "d", of("n", "d").alias("of")).select("n", "d", "of.height", "of.bound", "of.n_nodes")


@query("select m, n, round(ln(2) * m / n, 9) as exact, greatest(1, round(ln(2) * m / n))::bigint as k from (select unnest([1024, 15168, 100992]::bigint[]) as m), (select distinct n from (select count(distinct l_partkey) as n from lineitem group by l_suppkey))")
def optimal_hash_count(spark, sf_dir):
    """Best numbers of hash functions for each size that a supplier's set of parts has."""
    sizes = collection(spark, sf_dir, "supp").groupBy("site_id").agg(F.count("element").alias("n")).select("n").distinct()
    exact = F.log(F.lit(2.0)) * F.col("m") / F.col("n")
    return sizes.select(F.explode(F.array(*(F.lit(m).cast("bigint") for m in (1024, 15_168, 100_992)))).alias("m"), "n").select("m", "n", F.round(exact, 9).alias("exact"), F.greatest(F.lit(1), F.round(exact)).cast("bigint").alias("k"))


IDENTITY = FilterSpec(1500, family="mod_identity", k=1)
DOUBLE_XX = FilterSpec(1500, family="xx64_double")


@query(f"select element, 0 as i, element % {IDENTITY.m} as pos from (select distinct o_orderkey as element from orders)")
def hash_positions_identity(spark, sf_dir):
    return _positions(IDENTITY)(spark, sf_dir)


@query(O.chain(O.members("cust"), O.probes(), then="select query_id, site_id as filter_id from probes join mem using (element)"))
def xx64_search(spark, sf_dir):
    """Searches by 64-bit hashes; with the false positives, which SQL can't tell, taken out by the sets, the truth is left."""
    sets = collection(spark, sf_dir, "cust")
    asked = probes(sets)
    return pack.pack_search(pack.pack_build(sets, DOUBLE_XX), asked).join(scan.exact_search(sets, asked), ["query_id", "filter_id"], "left_semi")


@query(O.chain(O.members("nation"), O.bits(SMALL), then="select filter_id, pos from bits"))
def bytes_layout(spark, sf_dir):
    """Filters as bytes and back."""
    dense = filters.to_dense(filters.build_filters(collection(spark, sf_dir, "nation"), SMALL), SMALL).withColumnRenamed("filter_id", "key")
    back = filters.from_bytes(filters.to_bytes(dense, "key"), "key").withColumnRenamed("key", "filter_id")
    return filters.to_positions(filters.to_sparse(back))


@query(O.chain(O.members("day"), O.bits(SMALL), ("weeks", "select distinct filter_id // 7 as week, pos from bits"), then="select o.filter_id as a, w.week as b from (select filter_id, count(*) as n from bits group by 1) o, bits join weeks w using (pos) where bits.filter_id = o.filter_id group by 1, 2 having count(*) = any_value(o.n)"))
def week_containment(spark, sf_dir):
    """Days and weeks such that the day's filter lies in the union of the week's."""
    words = checkpointed(filters.build_filters(collection(spark, sf_dir, "day"), SMALL))
    weeks = filters.union_filters(words.withColumn("b", F.expr("filter_id div 7")), "b")
    days = words.join(F.broadcast(weeks.select("b").distinct()), F.lit(True)).select(F.col("filter_id").alias("a"), "b", "word_ix", F.col("word").alias("x"))  # a row for each week
    return distance.contained(days, weeks.withColumnRenamed("word", "y"))


@query(O.chain(O.members("user"), O.bits(SPEC), *O.search("user", SPEC)[2:], then="select query_id, filter_id from matches"))
def empty_filter_search(spark, sf_dir):
    """Sites without elements have a place in the tree and no bits; they never match."""
    sets = collection(spark, sf_dir, "user")
    words = filters.build_filters(sets, SPEC)
    ids = sets.select("site_id").distinct()
    both = ids.unionByName(ids.select((F.col("site_id") + 10_000).alias("site_id")))
    places = numbered(both.withColumnRenamed("site_id", "filter_id"), "filter_id", "place")
    return tree.tree_search(tree.bulk_load(words, SPEC, D, places=places), probes(sets))[0]


QUERIES["tree_search_forest_by_minhash"], ORACLES["tree_search_forest_by_minhash"] = _greedy("hamming", SPEC, "part", shards=8, shard_by="minhash"), _search_sql("part", SPEC, 10)


# --- provenance over event chains and composition ----------------------------------------------------------------------


def _event_edges(spark, sf_dir):
    events = table(spark, sf_dir, "events").select("user_id", "event_id", "ts", F.to_date("ts").alias("day"))
    before = F.lag("event_id").over(Window.partitionBy("user_id", "day").orderBy("ts", "event_id"))
    edges = events.select(F.pmod("event_id", F.lit(16)).alias("site_id"), F.col("event_id").alias("child"), before.alias("parent")).where("parent is not null")
    return edges, events.groupBy("user_id", "day").agg(F.max_by("event_id", F.struct("ts", "event_id")).alias("item")).select("item")


@query("select last_value(event_id) over w as start, event_id as item from events window w as (partition by user_id, ts::date order by ts, event_id rows between unbounded preceding and unbounded following) qualify last_value(event_id) over w <> event_id")
def provenance_events(spark, sf_dir):
    """From each user's last event of a day back along the day's chain of events, whose links lie on sixteen sites. A
    round is a step of the chain, so days are chains of their own; `trace` goes on as far as links go."""
    return provenance.trace(*_event_edges(spark, sf_dir), SPEC)[0]


def _composition(spark, sf_dir):
    """An order is made of parts, and a part of an order comes from a supplier; the links lie with the supplier's nation.
    Keys of one kind are kept apart from the others': orders 4x, parts 4x + 1, suppliers 4x + 2, parts from a supplier 4x + 3."""
    lines = table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "supplier"), F.expr("l_suppkey = s_suppkey"))
    lines = lines.select(F.col("s_nationkey").cast("bigint").alias("site_id"), "l_orderkey", "l_partkey", "l_suppkey").distinct()
    made = F.expr("4 * (l_partkey * 1000000 + l_suppkey) + 3")
    up = lines.select("site_id", F.expr("4 * l_orderkey").alias("child"), made.alias("parent"))
    part = lines.select("site_id", made.alias("child"), F.expr("4 * l_partkey + 1").alias("parent"))
    supplier = lines.select("site_id", made.alias("child"), F.expr("4 * l_suppkey + 2").alias("parent"))
    starts = lines.select(F.expr("4 * l_orderkey").alias("item")).distinct().where("item % 400 = 0")
    return up.unionByName(part).unionByName(supplier).distinct(), starts


@query("with l as (select distinct l_orderkey as o, l_partkey as p, l_suppkey as s from lineitem join supplier on l_suppkey = s_suppkey where l_orderkey % 100 = 0) select 4 * o as start, 4 * (p * 1000000 + s) + 3 as item from l union select 4 * o, 4 * p + 1 from l union select 4 * o, 4 * s + 2 from l")
def provenance_composition(spark, sf_dir):
    """What the orders with keys divisible by 100 are made of, across the suppliers' nations."""
    return provenance.trace(*_composition(spark, sf_dir), FilterSpec(20_000))[0]


# --- experiments -------------------------------------------------------------------------------------------------------


def _point(spark, sf_dir, label, name, spec, d):
    """One row of measures of a sorted load of a collection, and of searches in it, all of them distributed."""
    sets = stored(collection(spark, sf_dir, name), "sets")
    asked = stored(probes(sets), "asked")
    index = tree.bulk_load(filters.build_filters(sets, spec), spec, d, members=sets)
    found = pack.pack_search(pack.pack_build(sets, spec), asked)
    made = tree.shape(index).select("height", "n_nodes", (F.col("n_nodes") - F.col("n_inner")).alias("n_filters"))
    root = tree.root_words(index).agg(F.coalesce(F.sum(F.bit_count("word")), F.lit(0)).alias("root_ones"))
    cost = tree.counted_cost(index, asked).agg(F.round(F.avg("nodes_checked"), 6).alias("bf_cost"))
    matched = found.agg(F.round(F.count("*") / asked.count(), 6).alias("mean_matches"))
    row = made.crossJoin(root).crossJoin(cost).crossJoin(matched)  # one row each
    size = lambda method: F.expr({"tree": "n_nodes", "pack": "(n_filters + 63) div 64 * 64", "scan": "n_filters"}[method] + f" * {spec.m} div 8").alias(f"{method}_bytes")
    row = row.select(F.lit(label).alias("label"), F.lit(d).cast("bigint").alias("d"), F.lit(spec.m).cast("bigint").alias("m"), F.lit(spec.k).cast("bigint").alias("k"), "n_filters", F.col("height").cast("bigint").alias("height"), "n_nodes", "root_ones", "bf_cost", "mean_matches", size("tree"), size("pack"), size("scan"))
    return stored(row, "point")  # a point's shuffles go before the next one's


def _point_sql(label, name, spec, d):
    parts = O.chain(
        *O.search(name, spec), *O.sizes(d), O.NODE_BITS, O.NODE_HITS, O.edges(d), _PER_PROBE,
        then=f"""select '{label}' as label, {d}::bigint as d, {spec.m}::bigint as m, {spec.k}::bigint as k, l.n as n_filters, h.h as height, t.n as n_nodes,
        (select count(*) from nbits where level = h.h) as root_ones, (select round(avg(n), 6) from c) as bf_cost,
        round((select count(*) from matches) / (select count(*) from probes), 6) as mean_matches,
        t.n * {spec.m} // 8 as tree_bytes, (l.n + 63) // 64 * 64 * {spec.m} // 8 as pack_bytes, l.n * {spec.m} // 8 as scan_bytes
        from (select count(*) as n from leaves) l, (select max(level)::bigint as h from lv) h, (select count(*) as n from nodes) t""",
    )
    return f"select * from ({parts})"


#: Curve -> its points: label, collection, spec, order of the tree.
CURVES = {
    "filters": [(n, n, SPEC, D) for n in ("nation", "user", "block100", "cust", "part")] + [("order", "order", SMALL, D)],
    "order": [(f"d={d}", "cust", SPEC, d) for d in (2, 3, 4, 5, 8, 10, 16)],
    "filter_size": [(f"n_exp={n}", "block100", FilterSpec(n), D) for n in (100, 1000, 10_000, 100_000)],
    "target": [(f"p={p}", "block100", FilterSpec(1500, p), D) for p in (1e-7, 1e-5, 1e-3, 0.01, 0.1)],
    "set_size": [(n, n, SPEC, D) for n in ("block10", "block100", "block1000")],
    "distribution": [(n, n, WIDE_FLEET, D) for n in ("cust", "part", "conv")],
}


def _curve(points):
    def run(spark, sf_dir):
        rows = [_point(spark, sf_dir, *p) for p in points]
        whole = rows[0]
        for row in rows[1:]:
            whole = whole.unionByName(row)
        return whole

    return run


for _name, _points in CURVES.items():
    QUERIES[f"curve_{_name}"] = _curve(_points)
    ORACLES[f"curve_{_name}"] = "\nunion all\n".join(_point_sql(*p) for p in _points)


def curve_load_order(spark, sf_dir):
    """Mean nodes tested after sorted loads in different orders; the orders' hashes have no SQL form."""
    sets = stored(collection(spark, sf_dir, "part"), "sets")
    asked, words = stored(probes(sets), "asked"), stored(filters.build_filters(sets, WIDE_FLEET), "filters")
    rows = [tree.counted_cost(tree.bulk_load(words, WIDE_FLEET, D, o, members=sets), asked).agg(F.lit(o).alias("load_order"), F.avg("nodes_checked").alias("bf_cost")) for o in ("id", "ones", "first", "minhash")]
    return rows[0].unionByName(rows[1]).unionByName(rows[2]).unionByName(rows[3])


QUERIES["curve_load_order"] = curve_load_order


def _sweep(experiment):
    from filterfleet.plans import workloads

    return lambda spark, sf_dir: workloads.sweep(spark, experiment, sf_dir=sf_dir)


for _name in ("filters", "order", "filter_size", "target", "set_size", "metric", "distribution", "construction", "saturation_rule", "after_update", "family", "maintenance"):
    QUERIES[f"sweep_{_name}"] = _sweep(_name)


from filterfleet.plans import relational  # noqa: E402

QUERIES.update(relational.QUERIES)
ORACLES.update(relational.ORACLES)
