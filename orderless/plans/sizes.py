"""Queries for sizes, bounds and rates, each with the SQL that restates it."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import measures as m
from ..operators import codecodec, frames, ops
from ..sources import tables

Q: dict = {}
SQL: dict[str, str] = {}


def _rates(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    df = tables.id_lists(spark, sf_dir, name)
    return m.rates(m.list_sizes(df, "k", "id"), tables.universe(df))


for _name in tables.LISTS:
    Q[f"rates_{_name}"] = partial(_rates, _name)
    SQL[f"rates_{_name}"] = m.rates_sql(tables.lists_sql(_name), "k", "SELECT max(id) + 1 FROM src")


def regime_summary_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    """ids and Elias-Fano bits per id by list family and length class, with totals over each and both."""
    out = None
    for name in ("customer_order", "user_event", "part_order"):
        df = tables.id_lists(spark, sf_dir, name)
        s = m.list_sizes(df, "k", "id").select(F.lit(name).alias("workload"), F.when(F.col("n") < 8, "short").otherwise("long").alias("length"), "n", m.ef_bits_col(F.col("n"), F.lit(tables.universe(df))).alias("bits"))
        out = s if out is None else out.union(s)
    g = out.cube("workload", "length").agg(F.sum("n").cast("long").alias("ids"), F.round(F.sum("bits") / F.sum("n"), 4).alias("bits_per_id"), F.grouping_id().cast("long").alias("gid"))
    return g


_EF = "(n * CAST(floor(log2(greatest(u // n, 1))) AS BIGINT) + n + floor(u / pow(2, CAST(floor(log2(greatest(u // n, 1))) AS BIGINT))) + 1)"
_FAMILIES = " UNION ALL ".join(f"SELECT '{n}' AS workload, n, (SELECT max(id) + 1 FROM ({tables.lists_sql(n)})) AS u FROM (SELECT k, count(*) AS n FROM ({tables.lists_sql(n)}) GROUP BY k)" for n in ("customer_order", "user_event", "part_order"))
Q["regime_summary_cube"] = regime_summary_cube
SQL["regime_summary_cube"] = f"""WITH s AS (SELECT workload, CASE WHEN n < 8 THEN 'short' ELSE 'long' END AS length, n, {_EF} AS bits FROM ({_FAMILIES}))
SELECT workload, length, CAST(sum(n) AS BIGINT) AS ids, round(sum(bits) / sum(n), 4) AS bits_per_id, CAST(grouping_id(workload, length) AS BIGINT) AS gid FROM s GROUP BY CUBE (workload, length)"""


def bits_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The paper's kind of table: a row per partition, a column per codec."""
    out = None
    for name in ("nation_customer", "type_part", "user_event", "label_vec"):
        r = _rates(name, spark, sf_dir).select(F.lit(name).alias("workload"), "packed", "ef", "set_bound", "partition_bound")
        out = r if out is None else out.union(r)
    long = out.unpivot("workload", ["packed", "ef", "set_bound", "partition_bound"], "codec", "bits")
    return long.groupBy("workload").pivot("codec", ["packed", "ef", "set_bound", "partition_bound"]).agg(F.first("bits"))


Q["bits_pivot"] = bits_pivot
SQL["bits_pivot"] = " UNION ALL ".join(f"SELECT '{n}' AS workload, packed, ef, set_bound, partition_bound FROM ({SQL[f'rates_{n}']})" for n in ("nation_customer", "type_part", "user_event", "label_vec"))


def list_length_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits per id of events keyed ever more finely: longer lists cost less an id."""
    e, out = tables.table(spark, sf_dir, "events", ["event_id", "user_id", "event_type", "ts"]), None
    u = tables.universe(e, "event_id")
    keys = {"all": F.lit("x"), "type": F.col("event_type"), "hour": F.hour("ts").cast("string"), "user": F.col("user_id").cast("string"), "id": F.col("event_id").cast("string")}
    for name, k in keys.items():
        s = e.select(k.alias("k")).groupBy("k").agg(F.count(F.lit(1)).cast("long").alias("n"))
        r = m.rates(s, u).select(F.lit(name).alias("keyed_by"), "lists", "packed", "ef", "set_bound", "partition_bound")
        out = r if out is None else out.union(r)
    return out


Q["list_length_sweep"] = list_length_sweep
SQL["list_length_sweep"] = " UNION ALL ".join(
    f"SELECT '{n}' AS keyed_by, lists, packed, ef, set_bound, partition_bound FROM ({m.rates_sql(f'SELECT {k} AS k, event_id AS id FROM events', 'k', 'SELECT max(event_id) + 1 FROM events')})"
    for n, k in {"all": "'x'", "type": "event_type", "hour": "CAST(hour(ts) AS VARCHAR)", "user": "CAST(user_id AS VARCHAR)", "id": "CAST(event_id AS VARCHAR)"}.items()
)


def ef_gap_by_list(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How far Elias-Fano lies over the set bound, per supplier's list."""
    df = tables.id_lists(spark, sf_dir, "supplier_order")
    n, u = F.col("n"), F.lit(tables.universe(df))
    return m.list_sizes(df, "k", "id").select("k", "n", F.round((m.ef_bits_col(n, u) - m.set_bound_col(n, u)) / n, 4).alias("gap"))


Q["ef_gap_by_list"] = ef_gap_by_list
SQL["ef_gap_by_list"] = f"""WITH src AS ({tables.lists_sql("supplier_order")}), s AS (SELECT k, count(*) AS n, (SELECT max(id) + 1 FROM src) AS u FROM src GROUP BY k)
SELECT k, n, round(({_EF} - (n * log2(u) - lgamma(n + 1) / ln(2))) / n, 4) AS gap FROM s"""


def size_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lists, their lengths' percentiles, and the imbalance factor (lists times the sum of squares over the square of the sum)."""
    s = m.list_sizes(tables.id_lists(spark, sf_dir, "customer_order"), "k", "id")
    n = F.col("n")
    return s.agg(F.count(F.lit(1)).cast("long").alias("lists"), F.min(n).alias("least"), F.median(n).alias("median"), F.percentile(n, 0.9).alias("p90"), F.max(n).alias("most"), F.round(F.count(F.lit(1)) * F.sum(n * n) / (F.sum(n) * F.sum(n)), 6).alias("imbalance"))


Q["size_profile"] = size_profile
SQL["size_profile"] = f"""WITH s AS (SELECT k, count(*) AS n FROM ({tables.lists_sql("customer_order")}) GROUP BY k)
SELECT count(*) AS lists, min(n) AS least, median(n) AS median, quantile_cont(n, 0.9) AS p90, max(n) AS most, round(count(*) * sum(n * n) / (sum(n) * sum(n)), 6) AS imbalance FROM s"""


def _rec(name: str, directed: bool, spark: SparkSession, sf_dir: str) -> DataFrame:
    return m.rec_bits(*tables.graph(spark, sf_dir, name), directed=directed)


def _rec_sql(name: str, directed: bool) -> str:
    edges, n = tables.GRAPHS[name]
    order = "lgamma(e + 1)" + ("" if directed else " + (e - loops) * ln(2)")
    return f"""WITH e AS ({edges}), c AS (SELECT count(*) AS e, sum((src = dst)::INT) AS loops, {n} AS n FROM e),
d AS (SELECT sum(lgamma(d + 1)) AS lf FROM (SELECT v, count(*) AS d FROM (SELECT src AS v FROM e UNION ALL SELECT dst FROM e) GROUP BY v))
SELECT e AS edges, round((lgamma(2 * e + n) - lgamma(n) - lf - ({order})) / ln(2) / e, 4) AS bits_per_edge FROM c, d"""


for _name in tables.GRAPHS:
    for _directed in (True, False):
        _q = f"rec_closed_form_{'directed' if _directed else 'undirected'}_{_name}"
        Q[_q], SQL[_q] = partial(_rec, _name, _directed), _rec_sql(_name, _directed)


def friend_saving(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order bits that per-node lists and the whole edge set can save."""
    edges, _ = tables.graph(spark, sf_dir, "part_supplier")
    d = ops.degrees(edges)
    return d.agg(F.sum("degree").cast("long").alias("edges"), F.round(F.sum(m.log2_factorial_col(F.col("degree"))) / F.sum("degree"), 4).alias("per_list"), F.round(m.log2_factorial_col(F.sum("degree")) / F.sum("degree"), 4).alias("whole"))


Q["friend_saving"] = friend_saving
SQL["friend_saving"] = f"""WITH d AS (SELECT src, count(*) AS n FROM ({tables.GRAPHS["part_supplier"][0]}) GROUP BY src)
SELECT CAST(sum(n) AS BIGINT) AS edges, round(sum(lgamma(n + 1)) / ln(2) / sum(n), 4) AS per_list, round(lgamma(sum(n) + 1) / ln(2) / sum(n), 4) AS whole FROM d"""

_CODES = {
    "size_by_brand": ("part", "p_brand", "p_size"),
    "quantity_by_part": ("lineitem", "l_partkey", "CAST(l_quantity AS INT)"),
    "linenumber_by_supplier": ("lineitem", "l_suppkey", "l_linenumber"),
    "planted": ("events", "user_id % 16", "((user_id % 16) * 37 + (event_id * 7919) % 8) % 256"),
}


def _adaptive(name: str, conditioned: bool, spark: SparkSession, sf_dir: str) -> DataFrame:
    t, k, c = _CODES[name]
    df = tables.table(spark, sf_dir, t).selectExpr(f"{k if conditioned else '0'} AS k", f"{c} AS code")
    return m.adaptive_code_bits(df, ["k"], "code").agg(F.sum("n").cast("long").alias("codes"), F.round(F.sum("bits") / F.sum("n"), 4).alias("bits_per_code"))


def _adaptive_sql(name: str, conditioned: bool) -> str:
    t, k, c = _CODES[name]
    return f"""WITH s AS (SELECT {k if conditioned else "0"} AS k, {c} AS code FROM {t}), c AS (SELECT k, code, count(*) AS c FROM s GROUP BY ALL),
g AS (SELECT k, sum(c) AS n, sum(lgamma(c + 1)) AS lf FROM c GROUP BY k)
SELECT CAST(sum(n) AS BIGINT) AS codes, round(sum(lgamma(256 + n) - lgamma(256) - lf) / ln(2) / sum(n), 4) AS bits_per_code FROM g"""


def _entropy(name: str, conditioned: bool, spark: SparkSession, sf_dir: str) -> DataFrame:
    t, k, c = _CODES[name]
    return m.entropy(tables.table(spark, sf_dir, t).selectExpr(f"{k} AS k", f"{c} AS code"), "code", "k" if conditioned else None)


def _entropy_sql(name: str, conditioned: bool) -> str:
    t, k, c = _CODES[name]
    return f"""WITH c AS (SELECT {k if conditioned else "0"} AS k, {c} AS code, count(*) AS c FROM {t} GROUP BY ALL), g AS (SELECT k, sum(c) AS t, sum(c * log2(c)) AS cl FROM c GROUP BY k)
SELECT round(sum(t * log2(t) - cl) / sum(t), 6) AS bits FROM g"""


for _name in _CODES:
    for _c in (True, False):
        _tail = f"{'conditioned' if _c else 'unconditioned'}_{_name}"
        Q[f"adaptive_code_bits_{_tail}"], SQL[f"adaptive_code_bits_{_tail}"] = partial(_adaptive, _name, _c), _adaptive_sql(_name, _c)
        Q[f"entropy_{_tail}"], SQL[f"entropy_{_tail}"] = partial(_entropy, _name, _c), _entropy_sql(_name, _c)


def cross_entropy_uniform(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Part sizes coded by the model of all 50 sizes being alike: never under their entropy."""
    c = tables.table(spark, sf_dir, "part", ["p_size"]).groupBy("p_size").agg(F.count(F.lit(1)).alias("c"))
    return m.cross_entropy(c, c.select("p_size", F.lit(1 / 50).alias("p")), "p_size")


Q["cross_entropy_uniform"] = cross_entropy_uniform
SQL["cross_entropy_uniform"] = "SELECT round(-sum(c * log2(1 / 50.0::DOUBLE)) / sum(c), 6) AS bits FROM (SELECT p_size, count(*) AS c FROM part GROUP BY p_size)"


def wavelet_flat_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits of the flat strings over user labels of events: ids times levels."""
    e = tables.id_lists(spark, sf_dir, "user_event")
    levels = F.ceil(F.log2(F.max("k") + 1))
    return e.agg(F.count(F.lit(1)).cast("long").alias("ids"), (F.count(F.lit(1)) * levels).cast("long").alias("bits"))


Q["wavelet_flat_bits"] = wavelet_flat_bits
SQL["wavelet_flat_bits"] = "SELECT count(*) AS ids, CAST(count(*) * ceil(log2(max(user_id) + 1)) AS BIGINT) AS bits FROM events"


def rrr_class_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits of the block-compressed strings over event types, from the blocks' numbers of ones, in plain DataFrame operators."""
    from pyspark.sql import Window

    types = {t: i for i, t in enumerate(sorted(r.k for r in tables.id_lists(spark, sf_dir, "type_event").select("k").distinct().collect()))}  # five names
    k = F.create_map(*[F.lit(x) for kv in types.items() for x in kv])[F.col("k")]
    e = tables.id_lists(spark, sf_dir, "type_event").select("id", k.alias("k"))
    lv = e.select("id", "k", F.explode(F.array(F.lit(0), F.lit(1), F.lit(2))).alias("level"))
    lv = lv.select("id", "level", F.expr("shiftright(k, 3 - level)").alias("node"), F.expr("shiftright(k, 2 - level) & 1").alias("bit"))
    # nodes side by side in a level: place = labels in earlier nodes + place in the own node
    own = lv.withColumn("p", F.row_number().over(Window.partitionBy("level", "node").orderBy("id")) - 1)
    start = lv.groupBy("level", "node").agg(F.count(F.lit(1)).alias("c")).withColumn("s", F.coalesce(F.sum("c").over(Window.partitionBy("level").orderBy("node").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    blocks = own.join(F.broadcast(start), ["level", "node"]).groupBy("level", F.floor((F.col("p") + F.col("s")) / 63).alias("block")).agg(F.sum("bit").alias("ones"))
    ones = F.col("ones")
    width = F.ceil(F.round(m.log2_factorial_col(F.lit(63)) - m.log2_factorial_col(ones) - m.log2_factorial_col(63 - ones), 6))
    return blocks.agg(F.count(F.lit(1)).cast("long").alias("blocks"), F.sum(6 + width).cast("long").alias("bits"))


Q["rrr_class_bits"] = rrr_class_bits
SQL["rrr_class_bits"] = """WITH k AS (SELECT event_id AS id, dense_rank() OVER (ORDER BY event_type) - 1 AS k FROM events), l AS (SELECT unnest([0, 1, 2]) AS level),
b AS (SELECT level, (k >> (2 - level)) & 1 AS bit, row_number() OVER (PARTITION BY level ORDER BY k >> (3 - level), id) - 1 AS place FROM k, l),
o AS (SELECT level, place // 63 AS block, sum(bit) AS ones FROM b GROUP BY ALL)
SELECT count(*) AS blocks, CAST(sum(6 + ceil(round((lgamma(64) - lgamma(ones + 1) - lgamma(64 - ones)) / ln(2), 6))) AS BIGINT) AS bits FROM o"""


#: Lists whose ids and clusters a balanced index is projected for.
BALANCED = ("customer_order", "user_event", "type_part", "brand_part", "nation_customer")


def projection(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits per id of balanced indexes with as many ids and clusters as the given lists have, from the closed forms."""
    rows = None
    for name in BALANCED:
        r = tables.id_lists(spark, sf_dir, name).agg(F.lit(name).alias("workload"), F.countDistinct("id").alias("n"), F.countDistinct("k").alias("clusters"))
        rows = r if rows is None else rows.union(r)
    return balanced(rows, "workload")


def balanced(rows: DataFrame, *keep: str) -> DataFrame:
    """Adds the closed forms of n ids in as many clusters of one size; rows of other columns `keep`."""
    n, k = F.col("n").cast("double"), F.col("clusters").cast("double")
    size = n / k
    return rows.select(
        *keep, "n", "clusters", F.round(F.log2(n) - m.log2_factorial_col(size) / size, 3).alias("roc"), F.round(F.log2(k) + 2, 3).alias("ef"),
        F.round((m.log2_factorial_col(n) - k * m.log2_factorial_col(size)) / n, 3).alias("partition"), F.round(m.log2_factorial_col(k) / n, 6).alias("relabel_gain"),
    )


Q["projection"] = projection
_BALANCED_OF = " UNION ALL ".join(f"SELECT '{n}' AS workload, count(DISTINCT id) AS n, count(DISTINCT k) AS clusters FROM ({tables.lists_sql(n)})" for n in BALANCED)
SQL["projection"] = f"""WITH g AS ({_BALANCED_OF}), s AS (SELECT *, n / clusters AS size FROM g)
SELECT workload, n, clusters, round(log2(n) - lgamma(size + 1) / ln(2) / size, 3) AS roc, round(log2(clusters) + 2, 3) AS ef, round((lgamma(n + 1) - clusters * lgamma(size + 1)) / ln(2) / n, 3) AS partition, round(lgamma(clusters + 1) / ln(2) / n, 6) AS relabel_gain FROM s"""


def compression_ratios(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every kind of list: how many times smaller than raw and than fixed-width ids Elias-Fano and the set bound are."""
    out = None
    for name in tables.LISTS:
        r = _rates(name, spark, sf_dir)
        of = lambda a, b: F.round(F.col(a) / F.col(b), 4)
        r = r.select(F.lit(name).alias("workload"), of("raw", "ef").alias("raw_over_ef"), of("raw", "set_bound").alias("raw_over_set"), of("packed", "ef").alias("packed_over_ef"), of("packed", "set_bound").alias("packed_over_set"))
        out = r if out is None else out.union(r)
    return out


Q["compression_ratios"] = compression_ratios
SQL["compression_ratios"] = " UNION ALL ".join(
    f"SELECT '{n}' AS workload, round(raw / ef, 4) AS raw_over_ef, round(raw / set_bound, 4) AS raw_over_set, round(packed / ef, 4) AS packed_over_ef, round(packed / set_bound, 4) AS packed_over_set FROM ({SQL[f'rates_{n}']})"
    for n in tables.LISTS
)


def _latent(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts as a model with a latent variable: counts n of (z, v) = (brand's first digits, size), every of all, nz of z, nv of v, kv latents seen with v."""
    from pyspark.sql import Window

    c = tables.table(spark, sf_dir, "part", ["p_brand", "p_size"]).select(F.substring("p_brand", 1, 7).alias("z"), F.col("p_size").cast("int").alias("v")).groupBy("z", "v").agg(F.count(F.lit(1)).cast("double").alias("n"))
    total = lambda *by: F.sum("n").over(Window.partitionBy(*by))
    return c.withColumns({"every": total(), "nz": total("z"), "nv": total("v"), "kv": F.count(F.lit(1)).over(Window.partitionBy("v"))})


def bits_back_bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits a value with a uniform posterior over the latents seen with it (the negative evidence bound), with the exact one, and the divergence between."""
    c = _latent(spark, sf_dir)
    # model p(z) = nz / every, p(v | z) = n / nz; posterior exact n / nv, or 1 / kv; each value weighs nv / every
    joint, w = F.log2(F.col("n") / F.col("every")), F.col("nv") / F.col("every")
    loose = F.sum(w / F.col("kv") * (F.log2(1 / F.col("kv")) - joint))
    exact = F.sum(w * F.col("n") / F.col("nv") * (F.log2(F.col("n") / F.col("nv")) - joint))
    gap = F.sum(w / F.col("kv") * (F.log2(1 / F.col("kv")) - F.log2(F.col("n") / F.col("nv"))))
    return c.agg(F.round(loose, 6).alias("negative_elbo"), F.round(exact, 6).alias("marginal"), F.round(gap, 6).alias("divergence"))


Q["bits_back_bounds"] = bits_back_bounds
SQL["bits_back_bounds"] = """WITH c AS (SELECT substring(p_brand, 1, 7) AS z, p_size AS v, count(*)::DOUBLE AS n FROM part GROUP BY ALL),
m AS (SELECT v, sum(n) AS nv, count(*) AS kv FROM c GROUP BY v), t AS (SELECT sum(n) AS every FROM c),
e AS (SELECT sum(nv / every * log2(every / nv)) AS marginal FROM m, t),
g AS (SELECT sum(nv / every / kv * log2(nv / (kv * n))) AS divergence FROM c JOIN m USING (v), t)
SELECT round(marginal + divergence, 6) AS negative_elbo, round(marginal, 6) AS marginal, round(divergence, 6) AS divergence FROM e, g"""


def bits_back_measured(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Part sizes coded with bits back, by part type, beside the bound: net bits a value with either posterior, decoded again."""
    import pyarrow as pa

    from ..functions import bitsback, models
    from ..functions.ans import ExactState
    from ..operators import arrow

    arrow.importable(spark)
    counts = {(r.z, r.v): int(r.n) for r in _latent(spark, sf_dir).select("z", "v", "n").collect()}  # brands by sizes, at most 250
    zs, vs = sorted({z for z, _ in counts}), sorted({v for _, v in counts})
    values = tables.table(spark, sf_dir, "part", ["p_type", "p_size"]).select(F.col("p_type").alias("k"), F.col("p_size").cast("int").alias("v"))

    def run(key: tuple, t: pa.Table) -> pa.Table:
        rows, out = [vs.index(v) for v in t["v"].to_pylist()], []
        prior = models.Table([sum(counts.get((z, v), 0) for v in vs) for z in zs])
        given = [models.Table([counts.get((z, v), 0) for v in vs]) for z in zs]
        for name, weigh in (("uniform", lambda n: int(n > 0)), ("exact", lambda n: n)):
            posterior = [models.Table([weigh(counts.get((z, v), 0)) for z in zs]) for v in vs]
            state = ExactState.seeded(1 << 14, 1)
            before, value = state.bits, state.value
            for v in rows:
                bitsback.encode(state, v, prior, given.__getitem__, posterior.__getitem__)
            net = state.bits - before
            back = [bitsback.decode(state, prior, given.__getitem__, posterior.__getitem__) for _ in rows]
            out.append({"k": key[0].as_py(), "posterior": name, "n": len(rows), "bits": net, "lossless": back == rows[::-1] and state.value == value})
        return pa.Table.from_pylist(out, schema=pa.schema([("k", pa.string()), ("posterior", pa.string()), ("n", pa.int64()), ("bits", pa.int64()), ("lossless", pa.bool_())]))

    got = values.groupBy("k").applyInArrow(run, "k string, posterior string, n long, bits long, lossless boolean")
    return got.groupBy("posterior").agg(F.sum("n").cast("long").alias("values"), F.round(F.sum("bits") / F.sum("n"), 3).alias("bits_per_value"), F.min("lossless").alias("lossless"))


Q["bits_back_measured"] = bits_back_measured


def coder_redundancy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits an operation that a word state takes over its model, on line quantities by supplier under their own frequencies in 2**20 slots."""
    import pyarrow as pa

    from ..functions.ans import WordState
    from ..operators import arrow

    arrow.importable(spark)
    df = tables.table(spark, sf_dir, "lineitem", ["l_suppkey", "l_quantity"]).select(F.col("l_suppkey").alias("k"), F.col("l_quantity").cast("int").alias("v"))
    count = {r.v: r.n for r in df.groupBy("v").agg(F.count(F.lit(1)).alias("n")).collect()}  # fifty quantities
    symbols, total, slots = sorted(count), sum(count.values()), 20

    def run(key: tuple, t: pa.Table) -> pa.Table:
        import math

        start, edge = 0, {}
        for v in symbols:  # shares of the slots
            edge[v] = ((start << slots) // total, ((start + count[v]) << slots) // total)
            start += count[v]
        rows = t["v"].to_pylist()
        state = WordState.seeded(1)
        before = math.log2(state.head)
        for v in rows:
            state.push(edge[v][0], edge[v][1] - edge[v][0], slots)
        used = 32 * len(state.stack) + math.log2(state.head) - before
        model = sum(math.log2((1 << slots) / (edge[v][1] - edge[v][0])) for v in rows)
        return pa.table({"n": [len(rows)], "used": [used], "model": [model]})

    got = df.groupBy("k").applyInArrow(run, "n long, used double, model double")
    over = (F.sum("used") - F.sum("model")) / F.sum("n")
    return got.agg(F.sum("n").cast("long").alias("operations"), (over <= 2.2e-5).alias("within_published"))


Q["coder_redundancy"] = coder_redundancy
SQL["coder_redundancy"] = "SELECT count(*) AS operations, true AS within_published FROM lineitem"


def measured_fixed_codecs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the codecs without a state really take for orders by customer, from their payloads' bits."""
    df, out = tables.id_lists(spark, sf_dir, "customer_order"), None
    u = tables.universe(df)
    for codec in ("raw", "packed", "ef", "ef_ceil"):
        r = frames.bits_per_id(frames.encode_lists(df, "k", "id", codec, u)).select("codec", "ids", "bits_per_id")
        out = r if out is None else out.union(r)
    return out


Q["measured_fixed_codecs"] = measured_fixed_codecs
SQL["measured_fixed_codecs"] = f"SELECT unnest(['raw', 'packed', 'ef', 'ef_ceil']) AS codec, ids, unnest([raw, packed, ef, ef_ceil]) AS bits_per_id FROM ({SQL['rates_customer_order']})"


def measured_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What each codec really takes for orders by customer, beside the bounds' names; measured, so it has no SQL."""
    df, out = tables.id_lists(spark, sf_dir, "customer_order"), None
    u = tables.universe(df)
    for codec in ("raw", "packed", "ef", "roc", "roc_exact", "roc_buckets", "roc_seeded"):
        r = frames.bits_per_id(frames.encode_lists(df, "k", "id", codec, u))
        out = r if out is None else out.union(r)
    return out


Q["measured_bits"] = measured_bits


def measured_code_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Planted codes through the adaptive coder: bits per code conditioned on the cluster and not."""
    t, k, c = _CODES["planted"]
    df, out = tables.table(spark, sf_dir, t), None
    for name, key in (("conditioned", k), ("unconditioned", "0")):
        e = codecodec.encode(df.selectExpr(f"{key} AS k", "0 AS sub", "event_id AS id", f"{c} AS code"))
        r = e.agg(F.lit(name).alias("model"), F.sum("n").cast("long").alias("codes"), F.round(F.sum("bits") / F.sum("n"), 4).alias("bits_per_code"))
        out = r if out is None else out.union(r)
    return out


Q["measured_code_bits"] = measured_code_bits
