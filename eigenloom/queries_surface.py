"""Queries on sources, user functions, streams, neighbours and further solver workloads, beside those of `queries`."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eigenloom import apps, experiments
from eigenloom.functions import surface
from eigenloom.operators import dense, solver, tiles
from eigenloom.plans import lazy
from eigenloom.queries import _V, BITS, CUSTOMER_PART, EDGE, NORMAL, SQL, TRANSITIONS, USER_TYPE_EDGES, WIDTH, Q, _blocks, _counts, _power_sql, _values, query, wide
from eigenloom.sources import graphs, stores
from eigenloom.sources.graphs import table
from eigenloom.streaming import events as streams

EDGE_LIST = "select l_orderkey as i, l_partkey as j, l_quantity as w from lineitem"
ADJACENCY = f"select distinct i, j from (select i, j from ({TRANSITIONS}) union all select j, i from ({TRANSITIONS}))"
USER_TYPE = "select user_id::bigint as i, (dense_rank() over (order by event_type) - 1)::bigint as j from events"
NEAR = (
    "with e as (select vec_id, list_transform(embedding, lambda x: x::double) as v from embeddings), s as (select a.vec_id as i, b.vec_id as j, round(list_cosine_similarity(a.v, b.v), 9) as s from e a, e b where a.vec_id <> b.vec_id) "
    "select i, j, s, row_number() over (partition by i order by s desc, j) as rank from s qualify rank <= 10"
)


def _edge_list(spark, sf_dir) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("i"), F.col("l_partkey").alias("j"), F.col("l_quantity").alias("w"))


# sources and sinks
@query(EDGE_LIST)
def rel_csv_roundtrip(spark, sf_dir):
    return stores.roundtrip(_edge_list(spark, sf_dir), "csv")


@query(EDGE_LIST)
def rel_json_roundtrip(spark, sf_dir):
    return stores.roundtrip(_edge_list(spark, sf_dir), "json")


@query(EDGE_LIST)
def rel_orc_roundtrip(spark, sf_dir):
    return stores.roundtrip(_edge_list(spark, sf_dir), "orc")


@query(f"select i // 512 as band, count(*) as edges, count(distinct i) as rows, sum(w)::bigint as weight from ({CUSTOMER_PART}) group by 1")
def rel_partitioned_store(spark, sf_dir):
    held = stores.partitioned(graphs.customer_part(spark, sf_dir), 512)
    return held.groupBy("band").agg(F.count(F.lit(1)).alias("edges"), F.countDistinct("i").alias("rows"), F.sum("w").cast("long").alias("weight"))


@query(SQL["edges_recursive_matrix"])
def rel_generator_source(spark, sf_dir):
    """The generator's edges for the orders' keys."""
    return stores.generated(spark, 6, keys=table(spark, sf_dir, "orders").select(F.col("o_orderkey").cast("long").alias("id")))


# joins over the adjacency and over time
@query("select a.event_id as earlier, b.event_id as later from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour")
def rel_join_interval(spark, sf_dir):
    """Events of one user at most an hour apart: the later one enters its own hour and the one before, so a pair meets in exactly one bucket."""
    events = table(spark, sf_dir, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
    hour = 3_600_000_000
    early = events.select("user_id", F.col("event_id").alias("earlier"), F.col("at").alias("began"), F.floor(F.col("at") / hour).alias("bucket"))
    late = events.select("user_id", F.col("event_id").alias("later"), "at", F.explode(F.array(F.floor(F.col("at") / hour), F.floor(F.col("at") / hour) - 1)).alias("bucket"))
    return early.join(late, ["user_id", "bucket"]).filter((F.col("at") > F.col("began")) & (F.col("at") <= F.col("began") + hour)).select("earlier", "later")


@query(f"with a as ({ADJACENCY}) select x.i, y.j, count(*) as paths from a x join a y on x.j = y.i where x.i < y.j group by 1, 2")
def rel_two_hop(spark, sf_dir):
    a = graphs.user_adjacency(spark, sf_dir).select("i", "j")
    onward = a.select(F.col("i").alias("j"), F.col("j").alias("k"))
    return a.join(onward, "j").filter("i < k").groupBy("i", F.col("k").alias("j")).agg(F.count(F.lit(1)).alias("paths")).select("i", "j", "paths")


@query(f"with a as ({ADJACENCY}) select count(*) as triangles from a x join a y on x.j = y.i and x.i < x.j and y.i < y.j join a z on z.i = x.i and z.j = y.j")
def rel_triangles_exact(spark, sf_dir):
    """Each vertex points to neighbours of higher degree (ties by id), which bounds the wedges of a hub by the root of the edges."""
    a = graphs.user_adjacency(spark, sf_dir).select("i", "j")
    degree = a.groupBy("i").agg(F.count(F.lit(1)).alias("d"))
    ranked = a.join(degree, "i").join(degree.select(F.col("i").alias("j"), F.col("d").alias("e")), "j")
    up = ranked.filter(F.struct("d", "i") < F.struct(F.col("e").alias("d"), F.col("j").alias("i"))).select("i", "j")
    wedges = up.join(up.select(F.col("i").alias("j"), F.col("j").alias("k")), "j").select("i", "k")
    return wedges.join(up.select("i", F.col("j").alias("k")), ["i", "k"]).agg(F.count(F.lit(1)).alias("triangles"))


@query(f"select i, j, rank from ({NEAR}) where i % 100 = 0")
def win_topk_neighbours(spark, sf_dir):
    """The stated query set, ids divisible by 100, against all vectors."""
    rows = table(spark, sf_dir, "embeddings")
    return graphs.nearest(rows, rows.filter(F.col("vec_id") % 100 == 0), 10).select("i", "j", F.col("rank").cast("long").alias("rank"))


# plans and formats
@query(f"with e(edge) as (values (64::bigint), (256), (1024)), r as (select edge, i // edge as tr, j // edge as tc, i, count(*) as n from ({CUSTOMER_PART}), e group by 1, 2, 3, 4) select edge, round((sum(2 + 2 * n))::double / (select 8 * count(*) + 8 * (max(i) + 2) from ({CUSTOMER_PART})), 6) as ratio from r group by edge")
def storage_ratio(spark, sf_dir):
    edges = graphs.customer_part(spark, sf_dir)
    parts = [tiles.storage_report(edges, e).select(F.lit(e).cast("long").alias("edge"), F.round(F.col("code_bytes") / F.col("csr_bytes"), 6).alias("ratio")) for e in (64, 256, 1024)]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query(
    f"with t as (select b, greatest(1, 8388608 // (4 * 16 * b) // 1024) as side from (values (1), (2), (4), (8), (16)) as t(b)), c as (select distinct i // 1024 as tr, j // 1024 as tc from ({CUSTOMER_PART})) "
    "select b::int as b, side::int as side, count(distinct (tr // side, tc // side)) as super_tiles from t cross join c group by b, side"
)
def super_tile_plan(spark, sf_dir):
    """The side of a super tile by the block's width, and how many of them the tiles of customer by part make."""
    plan = spark.createDataFrame([(b, tiles.plan_super(b, 8 << 20, 4, 1024)) for b in (1, 2, 4, 8, 16)], "b int, side int")
    held = tiles.assigned(graphs.customer_part(spark, sf_dir), 1024).select("tr", "tc").distinct()
    made = held.crossJoin(F.broadcast(plan)).select("b", "side", F.floor(F.col("tr") / F.col("side")).alias("a"), F.floor(F.col("tc") / F.col("side")).alias("c")).distinct()
    return made.groupBy("b", "side").agg(F.count(F.lit(1)).alias("super_tiles"))


# solver workloads
PAGES = "select page_id as i, (dense_rank() over (order by path) - 1)::bigint as j, w from (select page_id, path, count(*)::double as w from (select page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as path from pages) group by 1, 2)"


@query(_power_sql(NORMAL.replace(CUSTOMER_PART, PAGES), f"(select distinct j as i from ({PAGES}))", 40, "sqrt"))
def top_sv_page_links(spark, sf_dir):
    """Web preset: two columns, 2k blocks."""
    edges = graphs.page_links(spark, sf_dir).persist()
    n = _counts(spark, sf_dir, "pages", "page_id"), edges.agg(F.max("j")).first()[0] + 1
    b, blocks = solver.preset(8, "web")
    found = solver.singular(spark, edges, *n, 8, b=b, blocks=blocks)
    found.values = found.values[:1]
    return _values(spark, found)


NEAR_EDGES = f"select i, j, max(w) as w from (select i, j, 1 - s as w from ({NEAR}) union all select j, i, 1 - s from ({NEAR})) group by 1, 2"


@query(_power_sql(NEAR_EDGES, f"(select vec_id as i from embeddings)", 40, ""))
def top_eig_neighbours(spark, sf_dir):
    """Clustered preset: a subspace four times as large."""
    b, blocks = solver.preset(1, "clustered")
    return _values(spark, solver.eigen(spark, graphs.vector_neighbours(spark, sf_dir), _counts(spark, sf_dir, "embeddings", "vec_id"), 1, b=b, blocks=blocks))


def _trade_backend(spark, sf_dir):
    forward, _back, cells = solver.array_product(graphs.nation_trade(spark, sf_dir), 25, 25)
    return solver.MemoryBackend(forward, 25, cells)


@query("select range::int as rank, true as small from range(4)")
def residual_flags(spark, sf_dir):
    """Explicit residuals A x - value x of each pair."""
    backend = _trade_backend(spark, sf_dir)
    found = solver.krylov_schur(backend, 4, b=2, blocks=6, want_vectors=True)
    rest = np.linalg.norm(backend.apply(found.vectors) - found.vectors * found.values, axis=0)
    return spark.createDataFrame([(k, bool(r <= 1e-6 * abs(v))) for k, (r, v) in enumerate(zip(rest, found.values))], "rank int, small boolean")


@query("select b::int as b, true as orthogonal from (values (1), (2), (4)) as t(b)")
def orthogonality_flags(spark, sf_dir):
    rows = [(b, bool(solver.krylov_schur(_trade_backend(spark, sf_dir), 4, b=b, blocks=8, want_vectors=True).orthogonality < 1e-10)) for b in (1, 2, 4)]
    return spark.createDataFrame(rows, "b int, orthogonal boolean")


@query("select b::int as b, true as agrees from (values (2), (3), (4)) as t(b)")
def block_vs_single_agree(spark, sf_dir):
    single = solver.krylov_schur(_trade_backend(spark, sf_dir), 4, b=1, blocks=10).values
    rows = [(b, bool(np.allclose(solver.krylov_schur(_trade_backend(spark, sf_dir), 4, b=b, blocks=5).values, single, rtol=1e-8))) for b in (2, 3, 4)]
    return spark.createDataFrame(rows, "b int, agrees boolean")


# user functions
@query("select page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) as host from pages")
def udx_scalar(spark, sf_dir):
    return table(spark, sf_dir, "pages").select("page_id", surface.host_of("url").alias("host"))


@query("select vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::double * x::double))), 4) as norm from embeddings")
def udx_pandas(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select("vec_id", F.round(surface.norm("embedding"), 4).alias("norm"))


@query("select i, sum(n * n)::double as squares from (select user_id::bigint as i, event_type, count(*) as n from events group by 1, 2) group by i")
def udx_grouped_agg(spark, sf_dir):
    return graphs.user_type(spark, sf_dir).groupBy("i").agg(surface.square_sum("w").alias("squares"))


@query(f"select i, count(*) as degree, max(j) as last from ({CUSTOMER_PART}) group by i")
def udx_apply_grouped(spark, sf_dir):
    return surface.row_profile(graphs.customer_part(spark, sf_dir))


@query("select n_nationkey::bigint as nation, (select count(*) from supplier where s_nationkey = n_nationkey) as n_left, (select count(*) from customer where c_nationkey = n_nationkey) as n_right from nation")
def udx_cogroup(spark, sf_dir):
    """Every nation once, as it joins a row of its own to both sides and takes it off again."""
    nations = table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("nation"))
    left = table(spark, sf_dir, "supplier").select(F.col("s_nationkey").cast("long").alias("nation"))
    right = table(spark, sf_dir, "customer").select(F.col("c_nationkey").cast("long").alias("nation"))
    return surface.side_counts(nations.union(left), nations.union(right), "nation").select("nation", (F.col("n_left") - 1).alias("n_left"), (F.col("n_right") - 1).alias("n_right"))


@query(f"select i // {EDGE} as tr, j // {EDGE} as tc, count(*) as cells from ({CUSTOMER_PART}) group by 1, 2")
def udx_map_arrow(spark, sf_dir):
    return surface.tile_keys(graphs.customer_part(spark, sf_dir), EDGE)


@query(CUSTOMER_PART)
def udx_udtf_cells(spark, sf_dir):
    surface.register(spark)
    coded = tiles.encoded(graphs.customer_part(spark, sf_dir), EDGE)
    return spark.sql(f"select c.i, c.j, c.w from {{coded}} t, lateral tile_cells(t.tr, t.tc, t.n_single, t.code, t.vals, {EDGE}) c", coded=coded)


@query("""select page_id, (row_number() over (partition by page_id order by k) - 1)::int as place, target from (select page_id, unnest(l) as target, unnest(range(1, len(l) + 1)) as k from (select page_id, regexp_extract_all(html, '<a\\s[^>]*href="([^"]*)"', 1) as l from pages))""")
def udx_udtf_links(spark, sf_dir):
    surface.register(spark)
    return spark.sql("select p.page_id, l.place, l.target from {pages} p, lateral html_links(p.html) l", pages=table(spark, sf_dir, "pages"))


@query("select o_custkey // 256 as tr, count(*) as n from orders group by 1")
def udx_sql_function(spark, sf_dir):
    surface.register(spark)
    return spark.sql("select tile_of(o_custkey, 256) as tr, count(*) as n from {orders} group by tile_of(o_custkey, 256)", orders=table(spark, sf_dir, "orders"))


# streams
@query("select event_type, strftime(slot - s * interval 1 hour, '%Y-%m-%d %H:%M:%S') as slot, count(*) as n from (select event_type, time_bucket(interval '1 hour', ts) as slot from events), (values (0), (1)) as t(s) group by 1, 2")
def stream_sliding(spark, sf_dir):
    return streams.sliding(spark, sf_dir)


@query("with g as (select user_id, ts, sum((before is null or ts >= before + interval 6 hours)::int) over (partition by user_id order by ts, event_id) as run from (select *, lag(ts) over (partition by user_id order by ts, event_id) as before from events)) select user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') as began, count(*) as n from g group by user_id, run")
def stream_session(spark, sf_dir):
    return streams.sessions(spark, sf_dir)


@query("with d as (select cast(ts as date) as day, ts, dayofmonth(ts) + 31 * (month(ts) - 1) as k from events) select strftime(day, '%Y-%m-%d') as day, count(*) as n from d where k > 10 and day + interval 1 day <= (select max(ts) from d where k > 10) - interval 1 day group by 1")
def stream_watermark_late(spark, sf_dir):
    return streams.late_dropped(spark, sf_dir)


@query("select c_nationkey, count(*) as n from events join customer on user_id = c_custkey group by 1")
def stream_static_join(spark, sf_dir):
    return streams.with_static(spark, sf_dir)


@query("select a.user_id, a.event_id as click, b.event_id as purchase from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts > a.ts and b.ts <= a.ts + interval 6 hours")
def stream_stream_interval(spark, sf_dir):
    return streams.click_then_purchase(spark, sf_dir)


@query("select user_id, event_type, count(*)::bigint as n from events group by 1, 2")
def stream_incremental_edges(spark, sf_dir):
    return streams.merged_edges(spark, sf_dir)


# lazy chains
@query("select c_custkey as i, " + ", ".join(f"({x})::double as x{c}" for c, x in enumerate([f"2 * {_V[1]} - 3 * {_V[4]}", f"4 * {_V[0]} + {_V[5]}", f"6 * {_V[3]} - 3 * {_V[6]}", f"8 * {_V[2]} - {_V[7]}"])) + " from customer")
def lazy_chain(spark, sf_dir):
    """Views, scalings, column scalings and a sum over two blocks, run as one projection."""
    a, b = (lazy.Tall.stored(x, WIDTH) for x in _blocks(spark, sf_dir))
    made = a.view([1, 0, 3, 2]).scale_columns([1, 2, 3, 4]).scale(2.0) + b.scale_columns([-3, 1, -3, -1])
    return wide(dense.to_rows(made.frame(), BITS))


# uses of the spectrum
@query("select n_nationkey::bigint as i, min(n_nationkey) over (partition by n_regionkey)::bigint as first_member from nation")
def app_spectral_clusters(spark, sf_dir):
    """Nations joined to those of their region: clusters are regions. A cluster is named by its least member."""
    nations = table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("i"), "n_regionkey")
    edges = nations.join(nations.select(F.col("i").alias("j"), "n_regionkey"), "n_regionkey").filter("i <> j").select("i", "j", F.lit(1.0).alias("w"))
    found = apps.spectral_clusters(spark, edges, 25, table(spark, sf_dir, "region").count())
    names = found.groupBy("cluster").agg(F.min("i").alias("first_member"))
    return found.join(names, "cluster").select("i", "first_member")


@query("select true as pure, true as same")
def app_cluster_quality(spark, sf_dir):
    """Purity and adjusted Rand index of the clusters of `app_spectral_clusters` against regions."""
    truth = table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("i"), F.col("n_regionkey").alias("label"))
    found = app_spectral_clusters(spark, sf_dir).withColumnRenamed("first_member", "cluster")
    return apps.purity(found, truth).select((F.col("purity") == 1).alias("pure"), (F.abs(F.col("adjusted_rand") - 1) < 1e-9).alias("same"))


@query("select range::int as rank, range = 5 as exact from range(1, 6)")
def app_low_rank(spark, sf_dir):
    """Whether the best approximation of each rank is exact: the user-by-type matrix has rank 5."""
    edges = graphs.user_type(spark, sf_dir).persist()
    found = solver.singular(spark, edges, _counts(spark, sf_dir, "events", "user_id"), 5, 5, b=1, blocks=5)
    return spark.createDataFrame([(k + 1, bool(e < 1e-6)) for k, e in enumerate(apps.low_rank_errors(edges, found.values))], "rank int, exact boolean")


# experiments whose outcome does not depend on the machine
@query("select true as larger_subspace_restarts_less, true as all_but_smallest_converge")
def exp_parameter_study(spark, sf_dir):
    rows = experiments.parameter_study(spark, sf_dir).collect()
    restarts = {b: [r["restarts"] for r in rows if r["b"] == b] for b in (1, 2, 4)}
    falls = all(list(v) == sorted(v, reverse=True) for v in restarts.values())
    return spark.createDataFrame([(falls, all(r["converged"] for r in rows if r["blocks"] * r["b"] >= 16))], "larger_subspace_restarts_less boolean, all_but_smallest_converge boolean")


@query("select true as share_measured, true as takes_most")
def exp_phase_share(spark, sf_dir):
    """By the clock of an external solve, reorthogonalisation takes more time than the multiplies."""
    found = experiments.timed_external(spark, stores.copied(graphs.user_adjacency(spark, sf_dir)), _counts(spark, sf_dir, "events", "user_id"), 4)
    spent = {p: sum(r[5] for r in found.ledger.rows if r[1] == p and r[2] == "time") for p in ("multiply", "reorthogonalise")}
    return spark.createDataFrame([(min(spent.values()) > 0, spent["reorthogonalise"] > spent["multiply"])], "share_measured boolean, takes_most boolean")


@query("select method, true as accurate, fewer as no_more_products_than_krylov from (values ('block Davidson', false), ('block Krylov-Schur', true), ('locally optimal', false), ('subspace iteration', false)) as t(method, fewer)")
def exp_solver_family(spark, sf_dir):
    """The block Krylov solver needs the fewest products of the block methods."""
    rows = {r["method"]: r for r in experiments.solver_family(spark, sf_dir).collect() if r["method"] != "single vector"}
    least = rows["block Krylov-Schur"]["products"]
    return spark.createDataFrame([(m, r["error"] < 1e-5, r["products"] <= least) for m, r in rows.items()], "method string, accurate boolean, no_more_products_than_krylov boolean")


@query("select graph, true as converged, true as residuals_small from (values ('customer by part'), ('page links')) as t(graph)")
def exp_web_svd(spark, sf_dir):
    """The web preset converges, and its vectors of both sides fit: A v = s u."""
    return experiments.web_svd(spark, sf_dir).select("graph", "converged", (F.col("residual") < 1e-3).alias("residuals_small"))


@query(_power_sql(f"select p.j as i, q.j as j, sum(p.w * q.w) as w from ({USER_TYPE_EDGES}) p join ({USER_TYPE_EDGES}) q on p.i = q.i group by 1, 2", "(select range as i from range(5))", 20, "sqrt"))
def stream_top_value(spark, sf_dir):
    """The leading singular value refreshed from the edges that micro-batches merged."""
    merged = streams.merged_edges(spark, sf_dir).persist()
    ids = graphs.dense_ids(merged, "event_type")
    edges = merged.join(F.broadcast(ids), "event_type").select(F.col("user_id").alias("i"), F.col("id").alias("j"), F.col("n").cast("double").alias("w"))
    return _values(spark, solver.singular(spark, edges, _counts(spark, sf_dir, "events", "user_id"), 5, 1, b=1, blocks=5))


def app_embedding_clusters(spark, sf_dir):
    """Purity and adjusted Rand index of ten spectral clusters of all embeddings' neighbour graph, by cosine similarity, against their labels. No SQL form."""
    rows = table(spark, sf_dir, "embeddings")
    edges = graphs.vector_neighbours(spark, sf_dir, 10, "similarity").filter("w > 0")
    found = apps.spectral_clusters(spark, edges, _counts(spark, sf_dir, "embeddings", "vec_id"), 10, blocks=20)
    return apps.purity(found, rows.select(F.col("vec_id").alias("i"), "label")).select(F.round("purity", 4).alias("purity"), F.round("adjusted_rand", 4).alias("adjusted_rand"))


Q["app_embedding_clusters"] = app_embedding_clusters
