"""The registered queries of the GLM engine and the SQL that must give the same rows."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from coordloom.operators import baselines, blocks, deal, losses, metrics, permute, reports, solvers, topology
from coordloom.plans import oracles as sql
from coordloom.plans import workloads
from coordloom.sources import features
from coordloom.sources.bounded import small
from coordloom.sources.features import read
from coordloom.sources.ids import densify
from coordloom.storage import Bucketed

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, oracle: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


def long_form(df: DataFrame) -> DataFrame:
    """(eid, y, pos, val) of dense or sparse examples."""
    if "x" in df.columns:
        return df.select("eid", "y", F.posexplode("x").alias("pos", "val")).withColumn("val", F.round("val", 6))
    return df.select("eid", "y", F.explode(F.arrays_zip("idx", "val")).alias("e")).select("eid", "y", F.col("e.idx").alias("pos"), F.round("e.val", 6).alias("val"))


def dense_sql(data: str) -> str:
    return f"select eid, y, (unnest(range(len(x))))::int as pos, round(unnest(x), 6) as val from ({data})"


def sparse_sql(data: str) -> str:
    return f"select eid, y, unnest(idx)::int as pos, round(unnest(val), 6) as val from ({data})"


# Fixtures

query("fx_line_matrix", dense_sql(sql.LINE))(lambda s, d: long_form(features.line_matrix(s, d)))
query("fx_embed_long", dense_sql(sql.EMBED))(lambda s, d: long_form(features.embed_matrix(s, d)))
query("fx_order_sparse", sparse_sql(sql.ORDER))(lambda s, d: long_form(features.order_sparse(s, d)))
query("fx_event_sparse", sparse_sql(sql.EVENT))(lambda s, d: long_form(features.event_sparse(s, d)))
query("fx_wide_line", sparse_sql(sql.WIDE))(lambda s, d: long_form(features.wide_line(s, d)))
query("fx_text_hash", f"select eid, y, i::int as pos, round(v, 6) as val from ({sql.TEXT}) where i is not null")(lambda s, d: long_form(features.text_hash(s, d)))
query("fx_synth_dense", dense_sql(sql.synth_dense("select c_custkey from customer", 100)))(lambda s, d: long_form(features.synth_dense_of(read(s, d, "customer").select(F.col("c_custkey").alias("id")))))
query("fx_synth_sparse", sparse_sql(sql.synth_sparse("select o_orderkey from orders", 1000, 10)))(lambda s, d: long_form(features.synth_sparse_of(read(s, d, "orders").select(F.col("o_orderkey").alias("id")))))

FIXTURES = {"embed": (features.embed_matrix, sql.EMBED), "line": (features.line_matrix, sql.LINE), "order": (features.order_sparse, sql.ORDER), "event": (features.event_sparse, sql.EVENT)}


@query("fx_split", " union all ".join(f"select '{k}' as fixture, y, {sql.MD5N.format(t='eid::varchar')} % 5 = 0 as held_out, count(*)::bigint as n from ({q}) group by all" for k, (_, q) in FIXTURES.items()))
def fx_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    parts = [f(spark, sf_dir).select(F.lit(k).alias("fixture"), "y", metrics.is_test(F.col("eid")).alias("held_out")) for k, (f, _) in FIXTURES.items()]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.groupBy("fixture", "y", "held_out").agg(F.count("*").alias("n"))


# Statistics


@query("st_shape", " union all ".join(f"select '{k}' as fixture, count(*)::bigint as n, sum(len({'x' if k in ('embed', 'line') else 'idx'}))::bigint as nnz from ({q})" for k, (_, q) in FIXTURES.items()))
def st_shape(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for k, (f, _) in FIXTURES.items():
        df = f(spark, sf_dir)
        part = df.agg(F.lit(k).alias("fixture"), F.count("*").alias("n"), F.sum(F.size("x" if "x" in df.columns else "idx")).alias("nnz"))
        out = part if out is None else out.unionByName(part)
    return out


DENSITY = f"select j::int as pos, round(count(*) / (select count(*) from orders), 6)::double as density from (select unnest(idx) as j from ({sql.ORDER})) group by j"


def order_density(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = features.order_sparse(spark, sf_dir)
    n = read(spark, sf_dir, "orders").count()
    return df.select(F.explode("idx").alias("pos")).groupBy("pos").agg((F.count("*") / F.lit(n)).alias("p"))


query("st_column_density", DENSITY)(lambda s, d: order_density(s, d).select("pos", F.round("p", 6).alias("density")))


@query("st_scaling", f"select pos, round(avg(val), 6) as mean, round(stddev_pop(val), 6) as sd from (select (unnest(range(len(x))))::int as pos, unnest(x) as val from ({sql.LINE})) group by pos")
def st_scaling(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = features.line_matrix(spark, sf_dir).select(F.posexplode("x").alias("pos", "val"))
    return rows.groupBy("pos").agg(F.round(F.avg("val"), 6).alias("mean"), F.round(F.stddev_pop("val"), 6).alias("sd"))


def squared_norm(x):
    return F.aggregate(F.transform(x, lambda v: v * v), F.lit(0.0), lambda a, v: a + v)


@query("st_norms", f"select 'embed' as fixture, round(min(q), 6) as lo, round(avg(q), 6) as mean, round(max(q), 6) as hi from (select list_dot_product(x, x) as q from ({sql.EMBED})) union all select 'order', round(min(q), 6), round(avg(q), 6), round(max(q), 6) from (select list_dot_product(val, val) as q from ({sql.ORDER}))")
def st_norms(spark: SparkSession, sf_dir: str) -> DataFrame:
    stat = lambda df, c, k: df.select(squared_norm(c).alias("q")).agg(F.lit(k).alias("fixture"), F.round(F.min("q"), 6).alias("lo"), F.round(F.avg("q"), 6).alias("mean"), F.round(F.max("q"), 6).alias("hi"))
    return stat(features.embed_matrix(spark, sf_dir), "x", "embed").unionByName(stat(features.order_sparse(spark, sf_dir), "val", "order"))


@query("st_label_cube", "select lang, source, grouping(lang)::int as g_lang, grouping(source)::int as g_source, count(*)::bigint as n, sum(quality)::bigint as good, sum(toxic)::bigint as toxic from documents join labels using (doc_id) group by cube (lang, source)")
def st_label_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = read(spark, sf_dir, "documents").select("doc_id", "lang", "source").join(read(spark, sf_dir, "labels"), "doc_id")
    return df.cube("lang", "source").agg(F.grouping("lang").cast("int").alias("g_lang"), F.grouping("source").cast("int").alias("g_source"), F.count("*").alias("n"), F.sum("quality").alias("good"), F.sum("toxic").alias("toxic"))


@query("st_tokens", "select lang, count(*)::bigint as n, sum(len(string_split(text, ' ')))::bigint as pieces, min(md5(text)) as first_digest from documents group by lang")
def st_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "documents").groupBy("lang").agg(F.count("*").alias("n"), F.sum(F.size(F.split("text", " "))).alias("pieces"), F.min(F.md5("text")).alias("first_digest"))


LINE_ORDER = sql.LINE_ORDER.split(", ")


@query("id_dense", f"select l_orderkey, l_linenumber, eid from (select *, row_number() over (order by {sql.LINE_ORDER}) - 1 as eid from lineitem)")
def id_dense(spark: SparkSession, sf_dir: str) -> DataFrame:
    return densify(read(spark, sf_dir, "lineitem").select(*LINE_ORDER), LINE_ORDER).select("l_orderkey", "l_linenumber", "eid")


# Buckets


@query("bk_assign", f"select eid, eid // 8 as bid, ((eid // 8) * 4 // (((select count(*) from embeddings) + 7) // 8))::int as gid from ({sql.EMBED})")
def bk_assign(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = features.embed_matrix(spark, sf_dir)
    p = blocks.pack(df, df.count(), 64, 8, 4, store=False)
    return p.frame.select(F.explode("eids").alias("eid"), "bid", "gid")


@query("bk_sizes", "select size, count(*)::bigint as n from (select count(*)::int as size from (select row_number() over () - 1 as eid from lineitem) group by eid // 7) group by size")
def bk_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = features.line_matrix(spark, sf_dir).select("eid", "y", "x")
    p = blocks.pack(df, df.count(), 6, 7, 1, store=False)
    return p.frame.groupBy(F.size("eids").alias("size")).agg(F.count("*").alias("n"))


@query("bk_roundtrip", sparse_sql(sql.ORDER))
def bk_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = features.order_sparse(spark, sf_dir)
    return long_form(blocks.unpack(blocks.pack(df, df.count(), 66, 16, 2)))


CHOICES = "(select * from (values (64), (128)) l(line), (values (1048576), (33554432)) c(llc), (select count(*)::bigint as n from lineitem union all select count(*) from orders union all select 500000 union all select 4194304 union all select 4194305))"


@query("bk_choose", f"select n, line, llc, (case when 8 * n > llc then line // 8 else 1 end)::int as bucket from {CHOICES}")
def bk_choose(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = [read(spark, sf_dir, t).count() for t in ("lineitem", "orders")] + [500_000, 4_194_304, 4_194_305]
    rows = [(n, line, llc, topology.choose_bucket(n, topology.Topology(1, 4, line, llc))) for n in counts for line in (64, 128) for llc in (1 << 20, 1 << 25)]
    return spark.createDataFrame(rows, "n long, line int, llc int, bucket int")


# Orders and dealing

NB = "((select count(*) from embeddings) + 4) // 5"


@query("pm_md5_order", f"select e::int as epoch, bid, row_number() over (partition by e order by md5(bid || ':' || e || ':42'), bid) - 1 as rank from (select unnest(range({NB})) as bid), range(3) t(e)")
def pm_md5_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    nb = -(-read(spark, sf_dir, "embeddings").count() // 5)
    out = None
    for e in range(3):
        part = spark.range(nb).select(F.lit(e).alias("epoch"), F.col("id").alias("bid"), permute.key(F.col("id"), e, 42, "md5", nb).alias("k"))
        out = part if out is None else out.unionByName(part)
    return out.select("epoch", "bid", (F.row_number().over(Window.partitionBy("epoch").orderBy("k", "bid")) - 1).cast("long").alias("rank"))


@query("pm_feistel_bijective", "select count(*)::bigint as n, count(*)::bigint as n_distinct, 0::bigint as lo, count(*)::bigint - 1 as hi from orders")
def pm_feistel_bijective(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = read(spark, sf_dir, "orders").count()
    k = spark.range(n).select(permute.key(F.col("id"), 1, 42, "feistel", n).alias("k"))
    return k.agg(F.count("*").alias("n"), F.countDistinct("k").alias("n_distinct"), F.min("k").alias("lo"), F.max("k").alias("hi"))


def _affine(n: int, epoch: int) -> tuple[int, int]:
    return permute.affine_constants(n, epoch, 42)


A0, A1 = _affine(100, 0), _affine(100, 1)


@query("pm_affine_trap", f"select count(*)::bigint as n, count_if((b * {A0[0]} + {A0[1]}) % 100 % 4 = (b * {A1[0]} + {A1[1]}) % 100 % 4)::bigint as same_mod, count_if((b * {A0[0]} + {A0[1]}) % 100 * 4 // 100 = (b * {A1[0]} + {A1[1]}) % 100 * 4 // 100)::bigint as same_chunk from range(100) t(b)")
def pm_affine_trap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """100 buckets, 4 workers: affine order with mod keeps residue classes together, contiguous runs don't."""
    k0, k1 = permute.key(F.col("id"), 0, 42, "affine", 100), permute.key(F.col("id"), 1, 42, "affine", 100)
    return spark.range(100).agg(F.count("*").alias("n"), F.count_if(k0 % 4 == k1 % 4).alias("same_mod"), F.count_if(F.floor(k0 * 4 / 100) == F.floor(k1 * 4 / 100)).alias("same_chunk"))


def dealt(spark: SparkSession, nb: int, groups: int, per: int, how: str, epochs: int = 2, bids: DataFrame | None = None) -> DataFrame:
    bids = spark.range(nb).select(F.col("id").alias("bid")) if bids is None else bids
    meta, out = bids.select("bid", F.floor(F.col("bid") * groups / nb).cast("int").alias("gid")), None
    for e in range(epochs):
        part = deal.assign(meta, nb, groups, per, how, e, 42).select(F.lit(e).alias("epoch"), "gid", "wid", "bid", "pos")
        out = part if out is None else out.unionByName(part)
    return out


def dealt_sql(nb: str, groups: int, per: int, rank: str) -> str:
    order = "k, bid" if rank == "dynamic" else "bid"
    return f"""with m as (select e::int as epoch, bid, (bid * {groups} // nb)::int as gid, md5(bid || ':' || e || ':42') as k from (select unnest(range(nb)) as bid, nb from (select {nb} as nb)), range(2) t(e)),
r as (select *, row_number() over (partition by epoch, gid order by {order}) - 1 as r, count(*) over (partition by epoch, gid) as g from m),
w as (select *, (gid * {per} + r * {per} // g)::int as wid from r)
select epoch, gid, wid, bid, row_number() over (partition by epoch, wid order by k, bid) - 1 as pos from w"""


def _nb(spark: SparkSession, sf_dir: str) -> int:
    return -(-read(spark, sf_dir, "embeddings").count() // 5)


def dealt_embed(spark: SparkSession, sf_dir: str, groups: int, per: int, how: str) -> DataFrame:
    """The buckets of 5 embeddings, taken from the examples themselves: an example that isn't whole is refused."""
    whole = F.when(F.size("x") == 64, F.col("eid")).otherwise(F.raise_error(F.lit("an embedding without 64 values")))
    numbers = densify(features.embed_matrix(spark, sf_dir).select(whole.alias("_e")), ["_e"], "eid")
    return dealt(spark, _nb(spark, sf_dir), groups, per, how, bids=numbers.select(F.floor(F.col("eid") / 5).cast("long").alias("bid")).distinct())


query("dl_static", dealt_sql(NB, 1, 4, "static"))(lambda s, d: dealt_embed(s, d, 1, 4, "static"))
query("dl_dynamic", dealt_sql(NB, 1, 4, "dynamic"))(lambda s, d: dealt_embed(s, d, 1, 4, "dynamic"))
query("dl_hier", dealt_sql(NB, 2, 2, "dynamic"))(lambda s, d: dealt_embed(s, d, 2, 2, "dynamic"))


@query("dl_complete", "select 0::bigint as missing, 0::bigint as extra")
def dl_complete(spark: SparkSession, sf_dir: str) -> DataFrame:
    nb = -(-read(spark, sf_dir, "orders").count() // 8)
    given, want = dealt(spark, nb, 2, 4, "dynamic", 1).select("bid"), spark.range(nb).select(F.col("id").alias("bid"))
    missing, extra = want.exceptAll(given).agg(F.count("*").alias("missing")), given.exceptAll(want).agg(F.count("*").alias("extra"))
    return missing.crossJoin(extra)  # two single rows


@query("dl_overlap", f"with d as ({dealt_sql('((select count(*) from orders) + 7) // 8', 1, 4, 'dynamic')}) select a.wid, count(*)::bigint as size, count(b.bid)::bigint as kept from (select * from d where epoch = 0) a left join (select * from d where epoch = 1) b on a.wid = b.wid and a.bid = b.bid group by a.wid")
def dl_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = dealt(spark, -(-read(spark, sf_dir, "orders").count() // 8), 1, 4, "dynamic")
    a, b = d.filter("epoch = 0").select("wid", "bid"), d.filter("epoch = 1").select("wid", "bid", F.lit(1).alias("again"))
    return a.join(b, ["wid", "bid"], "left").groupBy("wid").agg(F.count("*").alias("size"), F.count("again").alias("kept"))


# Placement

PLACE_SQL = """with m as (select * from (values ('X', 4, 8), ('P', 2, 20)) m(machine, nodes, cores)),
t as (select *, case when threads <= cores then 1 else (threads + cores - 1) // cores end as used from m, (values (1), (4), (8), (9), (16), (17), (32), (40)) t(threads), (values (0), (1)) d(data_node) where threads <= nodes * cores),
n as (select *, unnest(range(nodes)) as node from t),
r as (select *, row_number() over (partition by machine, threads, data_node order by node <> data_node, node) - 1 as rank from n)
select machine, threads, data_node, node::int as node, (threads // used + case when rank < threads % used then 1 else 0 end)::int as given from r where rank < used"""


#: Jobs of the orders: each asks for a machine, a number of threads and the node of its data.
JOBS_SQL = "select machine, (1 + o_orderkey % most)::int as threads, (o_custkey // 2 % 2)::int as data_node, count(*)::bigint as jobs from orders join (values ('X', 32, 0), ('P', 40, 1)) m(machine, most, side) on o_custkey % 2 = side group by all"
JOBS_PLACE_SQL = f"""with m as (select * from (values ('X', 4, 8), ('P', 2, 20)) m(machine, nodes, cores)),
t as (select *, case when threads <= cores then 1 else (threads + cores - 1) // cores end as used from m join ({JOBS_SQL}) using (machine)),
n as (select *, unnest(range(nodes)) as node from t),
r as (select *, row_number() over (partition by machine, threads, data_node order by node <> data_node, node) - 1 as rank from n)
select machine, threads, data_node, node::int as node, (threads // used + case when rank < threads % used then 1 else 0 end)::int as given, jobs from r where rank < used"""


@query("pl_placement", JOBS_PLACE_SQL)
def pl_placement(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Where the threads of each kind of job go, and how many jobs there are of the kind."""
    here = F.col("o_custkey") % 2 == 0
    asked = read(spark, sf_dir, "orders").select(F.when(here, "X").otherwise("P").alias("machine"), (1 + F.col("o_orderkey") % F.when(here, 32).otherwise(40)).cast("int").alias("threads"), (F.floor(F.col("o_custkey") / 2) % 2).cast("int").alias("data_node"))
    jobs = asked.groupBy("machine", "threads", "data_node").agg(F.count("*").alias("jobs"))
    rows = [(m, t, d, node, given) for m, top in topology.MACHINES.items() for t in range(1, top.nodes * top.cores + 1) for d in (0, 1) for node, given in topology.plan_placement(t, top, d)]
    placed = spark.createDataFrame(rows, "machine string, threads int, data_node int, node int, given int")
    return jobs.join(F.broadcast(placed), ["machine", "threads", "data_node"]).select("machine", "threads", "data_node", "node", "given", "jobs")


@query("pl_placement_tvf", PLACE_SQL)
def pl_placement_tvf(spark: SparkSession, sf_dir: str) -> DataFrame:
    from coordloom.functions import sql as functions

    functions.register(spark)
    return spark.sql("""select machine, t.threads, data_node, p.node, p.threads as given from (values ('X', 32), ('P', 40)) m(machine, most), (values (1), (4), (8), (9), (16), (17), (32), (40)) t(threads), (values (0), (1)) d(data_node),
      lateral plan_placement_tvf(case when t.threads <= most then machine else 'P' end, least(t.threads, 40), data_node) p where t.threads <= most""")


# Counted costs


@query("cm_traffic", "select n, line, n * line as plain_bytes, (8 * n + line - 1) // line * line as bucketed_bytes, (n + line // 8 - 1) // (line // 8) as permuted from (select count(*)::bigint as n from lineitem union all select count(*) from orders), (values (64), (128)) l(line)")
def cm_traffic(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = [(n, line, metrics.alpha_traffic(n, line, False), metrics.alpha_traffic(n, line, True), metrics.permuted(n, line // 8)) for n in (read(spark, sf_dir, t).count() for t in ("lineitem", "orders")) for line in (64, 128)]
    return spark.createDataFrame(rows, "n long, line int, plain_bytes long, bucketed_bytes long, permuted long")


@query("cm_sync", "select feature, d, k, g, p, (p * k * 8 * d)::bigint as flat, (p * g * 8 * d)::bigint as across, (p * k * 8 * d)::bigint as within from (select 'l_partkey' as feature, count(distinct l_partkey)::bigint as d from lineitem union all select 'l_suppkey', count(distinct l_suppkey) from lineitem union all select 'o_custkey', count(distinct o_custkey) from orders) d, (values (4), (16)) k(k), (values (1), (4)) g(g), (values (1), (2)) p(p)")
def cm_sync(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes of an epoch's syncs for models with one weight per key of a table."""
    keys = {"l_partkey": "lineitem", "l_suppkey": "lineitem", "o_custkey": "orders"}
    sizes = [(c, read(spark, sf_dir, t).select(c).distinct().count()) for c, t in keys.items()]
    rows = [(c, d, k, g, p, *metrics.sync_bytes(d, k, g, p).values()) for c, d in sizes for k in (4, 16) for g in (1, 4) for p in (1, 2)]
    return spark.createDataFrame(rows, "feature string, d long, k int, g int, p int, flat long, across long, within long")


@query("cm_shuffle", "select k, round((1 - 1.0 / k) * b, 3)::double as global_bytes, 0.0::double as in_group_bytes from (values (2), (4), (16)) k(k), (select sum(len(val) * 12)::double as b from (" + sql.ORDER + "))")
def cm_shuffle(spark: SparkSession, sf_dir: str) -> DataFrame:
    size = features.order_sparse(spark, sf_dir).agg(F.sum(F.size("val") * 12).cast("double").alias("b"))
    return size.select("b", F.explode(F.array(*map(F.lit, (2, 4, 16)))).alias("k")).select("k", F.round((1 - 1.0 / F.col("k")) * F.col("b"), 3).alias("global_bytes"), F.lit(0.0).alias("in_group_bytes"))


@query("cm_conflict", f"select k, round(sum(k * p - (1 - pow(1 - p, k))), 6) as expected_collisions, round(max(1 - pow(1 - p, k - 1)), 6) as worst from (select count(*)::double / (select count(*) from orders) as p from (select unnest(idx) as j from ({sql.ORDER})) group by j), (values (2), (8), (32)) k(k) group by k")
def cm_conflict(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = order_density(spark, sf_dir).select("p", F.explode(F.array(*map(F.lit, (2, 8, 32)))).alias("k"))
    return p.groupBy("k").agg(F.round(F.sum(metrics.collisions(F.col("p"), F.col("k"))), 6).alias("expected_collisions"), F.round(F.max(metrics.conflict(F.col("p"), F.col("k"))), 6).alias("worst"))


# Trajectories on the embeddings

LAM = 0.01


def packed_embed(spark: SparkSession, sf_dir: str, bucket: int = 1, groups: int = 1) -> blocks.Packed:
    df = features.embed_matrix(spark, sf_dir)
    return blocks.pack(df, df.count(), 64, bucket, groups)


def weights(spark: SparkSession, w) -> DataFrame:
    return spark.createDataFrame([(k, round(float(x), 6)) for k, x in enumerate(w)], "pos int, value double").withColumn("value", F.round("value", 6))


def trajectory(name: str, loss: str, bucket: int = 1, groups: int = 1, workers: int = 1, how: str = "dynamic", merge: str = "add", epochs: int = 2) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        spec = solvers.TrainSpec(loss, LAM, epochs, 0.0, workers=workers, deal=how, merge=merge)
        return weights(spark, solvers.fit(packed_embed(spark, sf_dir, bucket, groups), spec).model.w)

    query(name, sql.trajectory_sql(loss, LAM, bucket, epochs, "md5", 42, groups, workers, how, merge))(run)


trajectory("sd_ridge_seq", "ridge")
trajectory("sd_ridge_bucket", "ridge", 8)
trajectory("sd_logit_seq", "logistic")
trajectory("sd_hinge_seq", "hinge")
trajectory("sd_sqhinge_seq", "squared_hinge")
trajectory("sd_smooth_hinge_seq", "smooth_hinge")
trajectory("rp_static", "ridge", 5, 1, 4, "static")
trajectory("rp_dynamic", "ridge", 5, 1, 4, "dynamic")
trajectory("rp_hier", "logistic", 5, 2, 4, "dynamic")
trajectory("rp_merge_add", "logistic", 5, 1, 4, "dynamic", "add")
trajectory("rp_merge_avg", "ridge", 5, 1, 4, "dynamic", "average")


@query("rp_sync2", sql.trajectory_sql("ridge", LAM, 5, 2, "md5", 42, 1, 4, syncs=2))
def rp_sync2(spark: SparkSession, sf_dir: str) -> DataFrame:
    spec = solvers.TrainSpec("ridge", LAM, 2, 0.0, workers=4, syncs_per_epoch=2)
    return weights(spark, solvers.fit(packed_embed(spark, sf_dir, 5), spec).model.w)


@query("rp_global", sql.trajectory_sql("ridge", LAM, 5, 2, "md5", 42, 1, 4))
def rp_global(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Global dealing over two groups: the workers of one group that held all blocks."""
    spec = solvers.TrainSpec("ridge", LAM, 2, 0.0, workers=4, deal="global")
    return weights(spark, solvers.fit(packed_embed(spark, sf_dir, 5, 2), spec).model.w)


def lossy(name: str, lost: bool) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        spec = solvers.TrainSpec("ridge", LAM, 1, 0.0)
        return weights(spark, solvers.fit_lossy_async(packed_embed(spark, sf_dir), spec, 4, lost).model.w)

    query(name, sql.lossy_sql(LAM, 4, lost))(run)


lossy("ls_lossy_t4", True)
lossy("ls_atomic_t4", False)


#: |v - A alpha| by threads: synthetic dense and sparse, lineitem and orders.
query("ls_drift")(lambda s, d: workloads.drift(s, d, ("synth_dense", "synth_sparse", "line", "order"), solvers.TrainSpec("logistic", 1e-3, 30)))


# Exact solutions and evaluation

TWO = "list_transform(x, lambda v: v)[1:2]"


@query("ex_ridge2", f"""with s as (select count(*)::double as n, sum(x[1] * x[1]) as a, sum(x[1] * x[6]) as b, sum(x[6] * x[6]) as c, sum(x[1] * x[2]) as p, sum(x[6] * x[2]) as q from ({sql.LINE})), t as (select a / n + {LAM}::double as a, b / n as b, c / n + {LAM}::double as c, p / n as p, q / n as q from s)
select round((p * c - b * q) / (a * c - b * b), 6) as w0, round((a * q - b * p) / (a * c - b * b), 6) as w1 from t""")
def ex_ridge2(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Price on quantity and constant, by the exact solver."""
    df = features.line_matrix(spark, sf_dir).select("eid", F.col("x")[1].alias("y"), F.array(F.col("x")[0], F.col("x")[5]).alias("x"))
    w = baselines.fit_ridge_exact(blocks.pack(df, df.count(), 2, 1024), LAM).w
    return spark.createDataFrame([(round(float(w[0]), 6), round(float(w[1]), 6))], "w0 double, w1 double")


@query("ex_ridge_optimum", "select true as gradient_is_zero")
def ex_ridge_optimum(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = packed_embed(spark, sf_dir, 8)
    m = baselines.fit_ridge_exact(p, LAM)
    g = baselines.objective_gradient(p, m.w, "ridge", LAM)[1]
    return spark.createDataFrame([(bool(abs(g).max() < 1e-8),)], "gradient_is_zero boolean")


@query("ex_solver_agreement")
def ex_solver_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    spec = solvers.TrainSpec("logistic", LAM)
    return workloads.compare(spark, packed_embed(spark, sf_dir, 8), spec).select("variant", "status", F.round("objective", 3).alias("objective"))


PLANTED_W = "list_transform(range(64), lambda j: ((37 * j + 11) % 19 - 9) / 9.0::double)"


def planted_margin(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = [((37 * j + 11) % 19 - 9) / 9.0 for j in range(64)]
    return features.embed_matrix(spark, sf_dir).select("eid", "y", metrics.margin_dense(F.col("x"), w).alias("margin"))


MARGINS = f"(select eid, y, list_dot_product(x, {PLANTED_W}) as margin from ({sql.EMBED}))"
query("ev_margin", f"select eid, round(margin, 6) as margin from {MARGINS}")(lambda s, d: planted_margin(s, d).select("eid", F.round("margin", 6).alias("margin")))
query("ev_logloss", f"select count(*)::bigint as n, round(avg(greatest(-y * margin, 0) + ln(1 + exp(-abs(y * margin)))), 6) as logloss from {MARGINS}")(lambda s, d: metrics.logloss(planted_margin(s, d)).withColumn("logloss", F.round("logloss", 6)))
query("ev_accuracy", f"select round(avg(case when (margin >= 0) = (y > 0) then 1.0 else 0.0 end), 6)::double as accuracy from {MARGINS}")(lambda s, d: metrics.accuracy(planted_margin(s, d)).withColumn("accuracy", F.round("accuracy", 6)))
query("ev_confusion", f"select y > 0 as actual, margin >= 0 as predicted, count(*)::bigint as n from {MARGINS} group by all")(lambda s, d: metrics.confusion(planted_margin(s, d)))
query("ev_auc", f"with r as (select y, rank() over (order by margin) + (count(*) over (partition by margin) - 1) / 2.0::double as r from {MARGINS}) select round((sum(r) filter (y > 0) - count(*) filter (y > 0) * (count(*) filter (y > 0) + 1) / 2.0::double) / (count(*) filter (y > 0) * count(*) filter (y <= 0)), 6) as auc from r")(lambda s, d: metrics.auc(planted_margin(s, d)).withColumn("auc", F.round("auc", 6)))


@query("ev_primal_dual_gap", f"""with data as materialized ({sql.EMBED}), n as (select count(*)::double as n from data),
v as (select i, sum(y * 0.5 * xi) / ({LAM}::double * any_value(n)) as w from (select y, n, unnest(range(len(x))) as i, unnest(x) as xi from data, n) group by i), w as (select list(w order by i) as w from v)
select round(avg((list_dot_product(x, w) - y) ** 2) / 2 + {LAM / 2}::double * any_value(list_dot_product(w, w)), 6) as primal, round(-avg(0.125 - 0.5) - {LAM / 2}::double * any_value(list_dot_product(w, w)), 6) as dual from data, w""")
def ev_primal_dual_gap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ridge at alpha = y / 2 with w = A alpha / (lam n)."""
    df = features.embed_matrix(spark, sf_dir)
    n = df.count()
    v = df.select(F.posexplode("x").alias("i", "xi"), "y").groupBy("i").agg((F.sum(F.col("y") * 0.5 * F.col("xi")) / (LAM * n)).alias("w")).orderBy("i")
    w = [r["w"] for r in v.collect()]  # d numbers
    z = df.select("y", metrics.margin_dense(F.col("x"), w).alias("z"))
    norm = sum(x * x for x in w)
    return z.agg(F.round(F.avg((F.col("z") - F.col("y")) ** 2) / 2 + LAM / 2 * norm, 6).alias("primal"), F.round(-F.avg(F.lit(0.125 - 0.5)) - LAM / 2 * norm, 6).alias("dual"))


@query("ev_consistency", f"select j::int as pos, round(sum(y * 0.5), 6)::double as v from (select y, unnest(idx) as j from ({sql.ORDER})) group by j")
def ev_consistency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A alpha for alpha = y / 2, by exploding and summing: what v has to equal."""
    df = features.order_sparse(spark, sf_dir)
    return df.select("y", F.explode(F.arrays_zip("idx", "val")).alias("e")).groupBy(F.col("e.idx").alias("pos")).agg(F.round(F.sum(F.col("y") * 0.5 * F.col("e.val")), 6).alias("v"))


@query("ev_rel_change", "select round(sqrt(sum((a - b) ** 2) / sum(a ** 2)), 6) as rel_change from (select list_sum(embedding::double[]) as a, list_sum(embedding::double[]) * 0.9 as b from embeddings)")
def ev_rel_change(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = F.aggregate(F.col("embedding").cast("array<double>"), F.lit(0.0), lambda s, v: s + v)
    two = read(spark, sf_dir, "embeddings").select(a.alias("a"), (a * 0.9).alias("b"))
    return metrics.rel_change(two, "a", "b").withColumn("rel_change", F.round("rel_change", 6))


@query("ev_certificate", f"""with data as materialized ({sql.EMBED}), n as (select count(*)::double as n from data),
v as (select i, sum(y * 0.5 * xi) / ({LAM}::double * any_value(n)) as w from (select y, n, unnest(range(len(x))) as i, unnest(x) as xi from data, n) group by i), w as (select list(w order by i) as w from v)
select round(avg((list_dot_product(x, w) - y) ** 2) / 2 + {LAM / 2}::double * any_value(list_dot_product(w, w)), 6) as primal, round(-avg(0.125 - 0.5) - {LAM / 2}::double * any_value(list_dot_product(w, w)), 6) as dual, true as consistent from data, w""")
def ev_certificate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The library's certificate of the model with alpha = y / 2 and w = A alpha / (lam n)."""
    p = packed_embed(spark, sf_dir, 8, 2)
    half = p.plain().select("slot", "bid", F.transform("y", lambda y: y * 0.5).alias("alpha"))
    at_zero = baselines.objective_gradient(p, _zeros(64), "ridge", 0.0)[1]  # - A y / n
    c = metrics.certificate(p, solvers.Model(-0.5 / LAM * at_zero, Bucketed(half.repartition("slot"), "half", p.groups).frame(), {}), "ridge", LAM)
    return spark.createDataFrame([(round(c["primal"], 6), round(c["dual"], 6), c["drift"] < 1e-9)], "primal double, dual double, consistent boolean")


# Baselines, first steps


@query("bl_gradient0", f"select p::int as pos, coalesce(round(sum(-y * 0.5) / (select count(*) from orders), 6), 0.0) as g from range(66) r(p) left join (select y, unnest(idx) as j from ({sql.ORDER})) on j = p group by p")
def bl_gradient0(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = features.order_sparse(spark, sf_dir)
    g = baselines.objective_gradient(blocks.pack(df, df.count(), 66, 256), _zeros(66), "logistic", 0.0)[1]
    return spark.createDataFrame([(k, round(float(v), 6)) for k, v in enumerate(g)], "pos int, g double").withColumn("g", F.round("g", 6))


def _zeros(d: int):
    import numpy as np

    return np.zeros(d)


@query("bl_gram", f"select i::int as i, j::int as j, round(avg(x[i + 1] * x[j + 1]), 6) as g from ({sql.LINE}), range(6) a(i), range(6) b(j) group by all")
def bl_gram(spark: SparkSession, sf_dir: str) -> DataFrame:
    g, _, _, n = baselines.gram(features.line_matrix(spark, sf_dir))
    return spark.createDataFrame([(i, j, round(float(g[i, j]) / n, 6)) for i in range(6) for j in range(6)], "i int, j int, g double")


@query("bl_irls1", f"""with s as (select count(*)::double as n, sum(x[1] * x[1]) / 4 as a, sum(x[1]) / 4 as b, count(*) / 4.0::double as c, sum(y * x[1]) / 2 as p, sum(y) / 2 as q from ({sql.LINE})), t as (select a / n + {LAM}::double as a, b / n as b, c / n + {LAM}::double as c, p / n as p, q / n as q from s)
select round((p * c - b * q) / (a * c - b * b), 6) as w0, round((a * q - b * p) / (a * c - b * b), 6) as w1 from t""")
def bl_irls1(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = features.line_matrix(spark, sf_dir).select("eid", "y", F.array(F.col("x")[0], F.col("x")[5]).alias("x"))
    w = baselines.fit_newton(blocks.pack(df, df.count(), 2, 1024), solvers.TrainSpec("logistic", LAM, 1)).model.w
    return spark.createDataFrame([(round(float(w[0]), 6), round(float(w[1]), 6))], "w0 double, w1 double")


@query("bl_gd1", f"select i::int as pos, round(sum(0.5 * y * xi) / any_value(n), 6) as value from (select y, n, unnest(range(len(x))) as i, unnest(x) as xi from ({sql.EMBED}), (select count(*)::double as n from embeddings)) group by i")
def bl_gd1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return weights(spark, baselines.fit_gd(packed_embed(spark, sf_dir, 8), solvers.TrainSpec("logistic", LAM, 1)).model.w)


@query("bl_cap_predictors", f"with g as (select j, abs(round(sum(-y * 0.5 * v) / any_value(n), 9)) as g from (select eid, y, i as j, v, n from ({sql.TEXT}), (select count(*)::double as n from labels join documents using (doc_id))) where j is not null group by j) select j::int as pos from g order by g desc, j limit 50")
def bl_cap_predictors(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = features.text_hash(spark, sf_dir).drop("y_toxic")
    best = baselines.top_predictors(blocks.pack(df, df.count(), features.TEXT_DIM, 16), 50, "logistic")  # a top-k report
    return spark.createDataFrame([(j,) for j in best], "pos int")


query("bl_sag1", sql.sag_sql(LAM, 8))(lambda s, d: weights(s, baselines.fit_sag(packed_embed(s, d, 8), solvers.TrainSpec("ridge", LAM, 1, 0.0)).model.w))
query("bl_dcd")(lambda s, d: weights(s, baselines.fit_dcd(packed_embed(s, d, 8), solvers.TrainSpec("hinge", LAM)).model.w))
query("bl_dcd_logistic")(lambda s, d: weights(s, baselines.fit_dcd(packed_embed(s, d, 8), solvers.TrainSpec("logistic", LAM)).model.w))
query("bl_lbfgs")(lambda s, d: weights(s, baselines.fit_lbfgs(packed_embed(s, d, 8), solvers.TrainSpec("logistic", LAM)).model.w))
query("bl_sgd")(lambda s, d: weights(s, baselines.fit_sgd(packed_embed(s, d, 8), solvers.TrainSpec("logistic", LAM, 1)).model.w))
query("bl_auto")(lambda s, d: weights(s, baselines.fit_auto(packed_embed(s, d, 8), solvers.TrainSpec("logistic", LAM)).model.w))

LASSO_COLS = (0, 2, 3, 5)
_lasso_x = "[x[1], x[3], x[4], x[6]]"


def _lasso_sql(epochs: int = 3, l1: float = 0.01) -> str:
    """Coordinate descent on the Gram matrix, unrolled column by column."""
    out = f"with d as (select {_lasso_x} as x, x[2] as t from ({sql.LINE})), g as (select count(*)::double as n, {', '.join(f'sum(x[{i + 1}] * x[{j + 1}]) as g{i}{j}' for i in range(4) for j in range(4))}, {', '.join(f'sum(x[{i + 1}] * t) as b{i}' for i in range(4))} from d), s0 as (select *, 0.0::double as w0, 0.0::double as w1, 0.0::double as w2, 0.0::double as w3 from g)"
    k = 0
    for _ in range(epochs):
        for c in range(4):
            rho = f"(b{c} - ({' + '.join(f'g{c}{j} * w{j}' for j in range(4))}) + g{c}{c} * w{c})"
            out += f", s{k + 1} as (select * replace (sign({rho}) * greatest(abs({rho}) - n * {l1}::double, 0) / g{c}{c} as w{c}) from s{k})"
            k += 1
    return out + f" select round(w0, 6) as w0, round(w1, 6) as w1, round(w2, 6) as w2, round(w3, 6) as w3 from s{k}"


@query("sd_lasso_path", _lasso_sql())
def sd_lasso_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = features.line_matrix(spark, sf_dir).select(F.col("x")[1].alias("y"), F.array(*[F.col("x")[c] for c in LASSO_COLS]).alias("x"))
    beta, _ = baselines.fit_elastic_net(df, 0.01, 0.0, 3, 0.0)
    return spark.createDataFrame([tuple(round(float(b), 6) for b in beta)], "w0 double, w1 double, w2 double, w3 double")


@query("sd_epoch_objective", sql.objective_sql(LAM, 2, 42))
def sd_epoch_objective(spark: SparkSession, sf_dir: str) -> DataFrame:
    p, rows, model = packed_embed(spark, sf_dir), [], None
    for e in range(2):
        r = solvers.fit(p, solvers.TrainSpec("ridge", LAM, 1, 0.0, seed=42 + e), model)
        model = r.model
        c = metrics.certificate(p, model, "ridge", LAM)
        rows.append((e + 1, round(c["primal"], 6), round(c["dual"], 6), bool(c["gap"] >= -1e-12)))
    return spark.createDataFrame(rows, "epoch int, primal double, dual double, gap_ok boolean")


# Workloads (histories: rows only). Runs stop on the tolerance, or at 200 epochs and then say so.

EPOCHS = 200
#: The emulator's runs, one example after another in one task, stop at twice the epochs that the slowest published run takes.
LOCK_FREE_EPOCHS = 30
RIDGE = solvers.TrainSpec("ridge", LAM, EPOCHS)
query("wk_epochs_by_k")(lambda s, d: workloads.partitions_sweep(s, packed_embed(s, d, 5), RIDGE))
query("wk_dealing")(lambda s, d: workloads.dealing(s, packed_embed(s, d, 5), RIDGE))
query("wk_buckets")(lambda s, d: workloads.buckets(s, d, "embed", RIDGE))
query("wk_hier")(lambda s, d: workloads.hierarchy(s, d, "embed", replace(RIDGE, workers=4), bucket=5))
query("wk_bottlenecks")(lambda s, d: workloads.bottlenecks(s, packed_embed(s, d, 5), RIDGE))
# W1 on F6a and F1, W2 on F6b and F3
for _name, _fixture in {"wk_lock_free_dense": "synth_dense", "wk_lock_free_line": "line", "wk_lock_free_sparse": "synth_sparse", "wk_lock_free_order": "order"}.items():
    query(_name)(lambda s, d, f=_fixture: workloads.lock_free(s, workloads.packed_fixture(s, d, f, n=workloads.synthetic_rows(s, d)), solvers.TrainSpec("logistic", 2e-2, LOCK_FREE_EPOCHS)))
# Seconds per epoch; two epochs each, as that is the measure
for _name, _fixture in {"wk_scaling": "order", "wk_scaling_line": "line", "wk_scaling_wide": "wide"}.items():
    query(_name)(lambda s, d, f=_fixture: workloads.scaling(s, d, f, solvers.TrainSpec("logistic", 1e-3, workers=4)))
# W3 on F6a; W7, W8 and W9 on the stand-ins of the paper's data: F1 dense, F3 and F8 sparse
LOGIT = solvers.TrainSpec("logistic", LAM, EPOCHS)
query("wk_bottlenecks_synth")(lambda s, d: workloads.bottlenecks(s, workloads.packed_fixture(s, d, "synth_dense", 8, n=workloads.synthetic_rows(s, d)), LOGIT))
for _fixture in ("line", "order", "wide"):
    query(f"wk_dealing_{_fixture}")(lambda s, d, f=_fixture: workloads.dealing(s, workloads.packed_fixture(s, d, f, 8), LOGIT))
    query(f"wk_buckets_{_fixture}")(lambda s, d, f=_fixture: workloads.buckets(s, d, f, LOGIT))
    query(f"wk_hier_{_fixture}")(lambda s, d, f=_fixture: workloads.hierarchy(s, d, f, replace(LOGIT, workers=4), bucket=8))
# C4, C4a, C7 and C16 over the histories of W7
query("wk_measures")(lambda s, d: workloads.measures(workloads.dealing(s, packed_embed(s, d, 5), RIDGE, (1, 4, 16))))
# W5 and W10 on F2, F1, F3 and F8
for _name, _fixture in {"wk_compare": "embed", "wk_compare_line": "line", "wk_compare_order": "order", "wk_compare_wide": "wide"}.items():
    query(_name)(lambda s, d, f=_fixture: workloads.test_loss(s, *workloads.fixture(s, d, f), LOGIT))
query("wk_label_sorted")(lambda s, d: workloads.label_sorted(s, d, RIDGE))
query("wk_predictor_cap")(lambda s, d: workloads.predictor_cap(s, d, LOGIT, 200))


@query("wk_cutoffs", "select n, case when n > 500000 then 8 else 1 end as by_cutoff from (select count(*)::bigint as n from lineitem union all select count(*) from orders union all select 500000 union all select 500001)")
def wk_cutoffs(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = [read(spark, sf_dir, t).count() for t in ("lineitem", "orders")] + [500_000, 500_001]
    line64 = topology.Topology(1, 4, 64, 32 << 20)
    return spark.createDataFrame([(n, topology.choose_bucket(n, line64, 500_000)) for n in counts], "n long, by_cutoff int")


# Relational operators around training

query("jn_semi_labelled", "select lang, count(*)::bigint as n from documents where doc_id in (select doc_id from labels) group by lang")(lambda s, d: read(s, d, "documents").join(read(s, d, "labels"), "doc_id", "left_semi").groupBy("lang").agg(F.count("*").alias("n")))
query("jn_anti_unlabelled", "select lang, count(*)::bigint as n from documents where doc_id not in (select doc_id from labels) group by lang")(lambda s, d: read(s, d, "documents").join(read(s, d, "labels"), "doc_id", "left_anti").groupBy("lang").agg(F.count("*").alias("n")))


@query("jn_range_bucket", "select g, count(*)::bigint as n, min(o_orderkey) as lo, max(o_orderkey) as hi from orders join (select g, g * m // 7 as a, (g + 1) * m // 7 as b from range(7) t(g), (select max(o_orderkey) + 1 as m from orders)) on o_orderkey >= a and o_orderkey < b group by g")
def jn_range_bucket(spark: SparkSession, sf_dir: str) -> DataFrame:
    """eid ranges to groups by an offsets table: a range join with seven rows on one side."""
    o = read(spark, sf_dir, "orders").select("o_orderkey")
    m = o.agg((F.max("o_orderkey") + 1).alias("m"))
    bounds = spark.range(7).join(F.broadcast(m)).select(F.col("id").alias("g"), F.floor(F.col("id") * F.col("m") / 7).alias("a"), F.floor((F.col("id") + 1) * F.col("m") / 7).alias("b"))
    return o.join(small(bounds), (F.col("o_orderkey") >= F.col("a")) & (F.col("o_orderkey") < F.col("b"))).groupBy("g").agg(F.count("*").alias("n"), F.min("o_orderkey").alias("lo"), F.max("o_orderkey").alias("hi"))


@query("jn_asof_model", "select version, count(*)::bigint as n from (select e.event_id, arg_max(m.version, struct_pack(t := m.ts, v := m.version)) as version from events e left join (select event_id as version, user_id, ts from events where event_type = 'purchase') m on m.user_id = e.user_id and (m.ts < e.ts or (m.ts = e.ts and m.version <= e.event_id)) group by e.event_id) group by version")
def jn_asof_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Last purchase of the same user up to each event, by time and then number: a running value, no join and no list."""
    e = read(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    own = F.when(F.col("event_type") == "purchase", F.col("event_id"))
    return e.select(F.last(own, ignorenulls=True).over(w).alias("version")).groupBy("version").agg(F.count("*").alias("n"))


@query("jn_theta", "select a.pos as a, b.pos as b from (select j as pos, count(*) as c from (select unnest(idx) as j from (" + sql.ORDER + ")) group by j) a join (select j as pos, count(*) as c from (select unnest(idx) as j from (" + sql.ORDER + ")) group by j) b on a.pos < b.pos and a.c < b.c and b.c < 2 * a.c")
def jn_theta(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Column pairs of like density; at most d rows on either side."""
    c = features.order_sparse(spark, sf_dir).select(F.explode("idx").alias("pos")).groupBy("pos").agg(F.count("*").alias("c"))
    a, b = c.select(F.col("pos").alias("a"), F.col("c").alias("ca")), c.select(F.col("pos").alias("b"), F.col("c").alias("cb"))
    return a.join(small(b), (F.col("a") < F.col("b")) & (F.col("ca") < F.col("cb")) & (F.col("cb") < 2 * F.col("ca"))).select("a", "b")


def by_user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


query("wn_lag_gap", "select event_id, epoch_us(ts) - epoch_us(lag(ts) over (partition by user_id order by ts, event_id)) as gap from events")(lambda s, d: read(s, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", (F.col("us") - F.lag("us").over(by_user())).alias("gap")))
query("wn_running", "select event_id, round(sum(value) over (partition by user_id order by ts, event_id rows unbounded preceding), 4) as total from events")(lambda s, d: read(s, d, "events").select("event_id", F.round(F.sum("value").over(by_user().rowsBetween(Window.unboundedPreceding, 0)), 4).alias("total")))
query("wn_rank", "select o_orderkey, rank() over w as r, dense_rank() over w as dr, ntile(4) over (partition by o_custkey order by o_totalprice desc, o_orderkey) as nt from orders window w as (partition by o_custkey order by o_totalprice desc)")(
    lambda s, d: read(s, d, "orders").select("o_orderkey", F.rank().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"))).cast("long").alias("r"), F.dense_rank().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"))).cast("long").alias("dr"), F.ntile(4).over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")).cast("long").alias("nt"))
)
query("ag_rollup", "select l_returnflag, l_linestatus, count(*)::bigint as n, round(sum(l_quantity), 2) as quantity from lineitem group by rollup (l_returnflag, l_linestatus)")(lambda s, d: read(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity")))
query("ag_pivot", "select l_returnflag, count(*) filter (l_linestatus = 'F')::bigint as F, count(*) filter (l_linestatus = 'O')::bigint as O from lineitem group by 1")(lambda s, d: read(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count().na.fill(0))
query("ag_moments", "select round(avg(l_extendedprice), 3) as mean, round(var_samp(l_quantity), 6) as variance, round(corr(l_quantity, l_extendedprice), 6) as corr, round(covar_pop(l_quantity, l_tax), 6) as cov, round(regr_slope(l_extendedprice, l_quantity), 4) as slope from lineitem")(
    lambda s, d: read(s, d, "lineitem").agg(F.round(F.avg("l_extendedprice"), 3).alias("mean"), F.round(F.var_samp("l_quantity"), 6).alias("variance"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("corr"), F.round(F.covar_pop("l_quantity", "l_tax"), 6).alias("cov"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"))
)
query("ag_distinct", "select event_type, count(distinct user_id)::bigint as users, count(*)::bigint as n from events group by event_type")(lambda s, d: read(s, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.count("*").alias("n")))
query("js_props", "select (props->>'$.k')::int as k, count(*)::bigint as n from events group by 1")(lambda s, d: read(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("int").alias("k")).agg(F.count("*").alias("n")))


# Streams over what is there


def streamed(name: str, build: Callable[[DataFrame], DataFrame], oracle: str, mode: str = "complete") -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        from coordloom.streaming import events

        schema = read(spark, sf_dir, "events").schema
        stream = _events(spark, sf_dir, schema)
        return events.run_available(build(stream.withColumn("ts", F.col("ts").cast("timestamp"))), name, mode)

    query(name, oracle)(run)


def _events(spark: SparkSession, sf_dir: str, schema) -> DataFrame:
    return spark.readStream.schema(schema).parquet(f"{sf_dir}/events.parquet*")


def _tumbling(e: DataFrame) -> DataFrame:
    from coordloom.streaming.events import windowed

    return windowed(e).select(F.unix_seconds("start").alias("start"), "n", "n_purchase")


def _sliding(e: DataFrame) -> DataFrame:
    from coordloom.streaming.events import windowed

    return windowed(e, "1 hour", "30 minutes").select(F.unix_seconds("start").alias("start"), "n", "n_purchase")


def _session(e: DataFrame) -> DataFrame:
    from coordloom.streaming.events import sessions

    return sessions(e).select("user_id", F.unix_seconds("start").alias("start"), "n")


_COUNTS = "count(*)::bigint as n, count(*) filter (event_type = 'purchase')::bigint as n_purchase"
streamed("ss_tumbling", _tumbling, f"select epoch(date_trunc('hour', ts))::bigint as start, {_COUNTS} from events group by 1")
streamed("ss_sliding", _sliding, f"select s as start, {_COUNTS} from (select *, unnest([floor(epoch(ts))::bigint // 1800 * 1800, floor(epoch(ts))::bigint // 1800 * 1800 - 1800]) as s from (select event_type, ts from events)) group by s")
streamed("ss_session", _session, "select user_id, min(t)::bigint as start, count(*)::bigint as n from (select *, sum(case when g is null or epoch_us(ts) - g >= 1800000000 then 1 else 0 end) over (partition by user_id order by ts, event_id) as s, floor(epoch(ts)) as t from (select *, epoch_us(lag(ts) over (partition by user_id order by ts, event_id)) as g from events)) group by user_id, s")


@query("sql_predict", f"select eid, y, round(margin, 6) as margin, round(1 / (1 + exp(-margin)), 6) as prob from {MARGINS}")
def sql_predict(spark: SparkSession, sf_dir: str) -> DataFrame:
    from coordloom.functions.sql import sql_predict as predict

    return predict(features.embed_matrix(spark, sf_dir), [((37 * j + 11) % 19 - 9) / 9.0 for j in range(64)]).select("eid", "y", F.round("margin", 6).alias("margin"), F.round("prob", 6).alias("prob"))


@query("step_columns", f"select eid, round({sql.step_sql('ridge', 'z', 'q', 'y', '0.25', '(q / 5.0::double)')}, 6) as ridge, round({sql.step_sql('hinge', 'z', 'q', 'y', '(y * 0.25)', '(q / 5.0::double)')}, 6) as hinge from (select eid, y, margin as z, 1.0::double as q from {MARGINS})")
def step_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    z = planted_margin(spark, sf_dir).withColumn("q", F.lit(1.0))
    s = F.col("q") / 5.0
    return z.select("eid", F.round(losses.step_expr("ridge", F.col("margin"), F.col("q"), F.col("y"), F.lit(0.25), s), 6).alias("ridge"), F.round(losses.step_expr("hinge", F.col("margin"), F.col("q"), F.col("y"), F.col("y") * 0.25, s), 6).alias("hinge"))


#: A report over ``lineitem``: its flags as variants, its line numbers as workers, its quantities (whole numbers) as seconds.
REPORT_SQL = """(select case l_returnflag when 'R' then 'static' when 'A' then 'dynamic' else 'lock-free ' || l_linenumber end as variant, l_linenumber as workers, count(*)::int as epochs,
  sum(l_quantity) as seconds, case when 2 * count(*) filter (l_linestatus = 'F') >= count(*) then 'converged' else 'wrong' end as status from lineitem group by all) r"""


def _report(spark: SparkSession, sf_dir: str) -> DataFrame:
    variant = F.when(F.col("l_returnflag") == "R", "static").when(F.col("l_returnflag") == "A", "dynamic").otherwise(F.concat(F.lit("lock-free "), F.col("l_linenumber")))
    status = F.when(2 * F.count_if(F.col("l_linestatus") == "F") >= F.count("*"), "converged").otherwise("wrong")
    return read(spark, sf_dir, "lineitem").groupBy(variant.alias("variant"), F.col("l_linenumber").alias("workers")).agg(F.count("*").cast("int").alias("epochs"), F.sum("l_quantity").alias("seconds"), status.alias("status"))


@query("ms_mean_speedup", f"select r.variant as against, round(avg(b.seconds / r.seconds), 2) as mean, max(b.seconds / r.seconds) as best from {REPORT_SQL} join (select workers, seconds from {REPORT_SQL} where variant = 'static') b using (workers) group by 1")
def ms_mean_speedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean and best speed-up of the static runs over each variant; a test recomputes the published means."""
    return reports.mean_speedup(reports.speedup(_report(spark, sf_dir), "static").select(F.col("variant").alias("against"), "speedup"))


query("ms_speedup", f"select r.variant, r.workers, b.seconds / r.seconds as speedup from {REPORT_SQL} join (select workers, seconds from {REPORT_SQL} where variant = 'static') b using (workers)")(lambda s, d: reports.speedup(_report(s, d), "static").select("variant", "workers", "speedup"))
query("ms_reduction", f"select avg(100 * (1 - v / b)) as percent from (select workers, max(epochs) filter (variant = 'static')::double as b, max(epochs) filter (variant = 'dynamic')::double as v from {REPORT_SQL} group by workers)")(lambda s, d: reports.reduction(_report(s, d).filter("variant in ('static', 'dynamic')"), "static", "dynamic", "epochs"))
query("ms_status", f"select status, count(*)::bigint as n from {REPORT_SQL} group by status")(lambda s, d: reports.status_counts(_report(s, d)))
query("ms_best_valid", f"select arg_min(variant, seconds) as variant, min(seconds) as seconds from {REPORT_SQL} where variant like 'lock-free%' and status = 'converged'")(lambda s, d: reports.best_valid(_report(s, d)))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The combined solver on the orders, on its own choice of buckets and groups: history by epoch, to the tolerance."""
    df, d = workloads.fixture(spark, sf_dir, "order")
    n = df.count()
    spec, unit, groups = solvers.fit_auto_spec(n, spark.sparkContext.defaultParallelism, loss="logistic", lam=LAM, max_epochs=EPOCHS)
    packed = blocks.pack(df, n, d, workloads.rows_per_block(n, spec.workers, unit), groups, unit=unit)
    result = solvers.fit(packed, spec, variant="combined")
    packed.release()
    return result.history(spark)


query("flagship")(flagship)
