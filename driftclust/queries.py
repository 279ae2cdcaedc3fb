"""Queries of the clustering engine and the SQL that they are checked against."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import sql_functions
from .operators import chunks, features, map_frames, metrics, planted, sampler
from .operators.baselines import METHODS
from .params import Params
from .plans import experiments, pipeline
from .sources import tables

_QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_SQL: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        key = name or f.__name__
        _QUERIES[key] = f
        if sql:
            _SQL[key] = sql
        return f

    return add


def _t(spark: SparkSession, d: str, *names: str):
    out = [tables.table(spark, d, n) for n in names]
    return out[0] if len(out) == 1 else out


def r(c, digits: int = 6):
    """Rounded, without a negative zero."""
    return F.round(c, digits) + F.lit(0.0)


def _lineitem(spark, d):
    """Objects of lineitem: label is the return flag, cluster the line status."""
    cols = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
    return _t(spark, d, "lineitem").select("l_returnflag", "l_linestatus", F.col("l_returnflag").alias("label"), F.col("l_linestatus").alias("cluster"), F.array(*[F.col(c).cast("double") for c in cols]).alias("x"))


def _emb(spark, d):
    return _t(spark, d, "embeddings").select(F.col("vec_id").alias("obj_id"), F.col("embedding").cast("array<double>").alias("x"), "label")


def _events(spark, d):
    e = _t(spark, d, "events")
    return e.select(F.col("event_id").alias("obj_id"), F.array(F.col("value"), F.hour("ts").cast("double"), F.get_json_object("props", "$.k").cast("double")).alias("x"), F.col("event_type").alias("label"), "ts", "value")


# --- Problem-level quantities, chunks, features ------------------------------


@query("select count(*) as n, cast(epoch(time_bucket(interval '864 minutes', ts, timestamp '2024-01-01')) as bigint) as chunk_id from events group by 2")
def chunk_windows_events(spark, d):
    return chunks.by_time(_t(spark, d, "events")).groupBy("chunk_id").agg(F.count("*").alias("n"))


@query("select cast(floor((row_number() over (order by o_orderkey) - 1) / 500) as bigint) as chunk_id, o_orderkey from orders")
def chunk_count_orders(spark, d):
    return chunks.by_count(_t(spark, d, "orders"), "o_orderkey", 500).select("chunk_id", "o_orderkey")


@query("select p_partkey % 7 as chunk_id, count(*) as n from part group by 1")
def chunk_mod_part(spark, d):
    return chunks.by_mod(_t(spark, d, "part"), "p_partkey", 7).groupBy("chunk_id").agg(F.count("*").alias("n"))


_SSQ = "with c as (select l_returnflag, avg(l_quantity) a, avg(l_extendedprice) b, avg(l_discount) c, avg(l_tax) e from lineitem group by 1) select round(sum({}), 2) as ssq from lineitem join c using (l_returnflag)"
_D2 = "(l_quantity-a)*(l_quantity-a)+(l_extendedprice-b)*(l_extendedprice-b)+(l_discount-c)*(l_discount-c)+(l_tax-e)*(l_tax-e)"


@query(_SSQ.format(f"sqrt({_D2})"))
def ssq_p1_lineitem(spark, d):
    return metrics.ssq(_lineitem(spark, d).withColumn("cluster", F.col("label"))).select(F.round("ssq", 2).alias("ssq"))


@query(_SSQ.replace("sum({}), 2", "sum({}) / 1e6, 2").format(_D2))
def ssq_p2_lineitem(spark, d):
    return metrics.ssq(_lineitem(spark, d).withColumn("cluster", F.col("label")), power=2).select(F.round(F.col("ssq") / 1e6, 2).alias("ssq"))


@query("with n as (select l_linenumber, l_returnflag, l_linestatus, count(*) n from lineitem group by all) select round(max(n) / min(n), 6) as ratio, count(*) as k from n")
def imbalance_ratio_all(spark, d):
    li = _t(spark, d, "lineitem").select(F.concat_ws("/", "l_linenumber", "l_returnflag", "l_linestatus").alias("cluster"))
    return metrics.imbalance(li).select(r(F.col("ratio")).alias("ratio"), "k")


@query("with n as (select cast(date_diff('day', date '2024-01-01', cast(ts as date)) as bigint) chunk_id, event_type, count(*) n from events group by all), s as (select chunk_id, max(n)/min(n) as ratio, count(*) as k from n group by 1) select chunk_id, round(ratio, 6) as ratio, k, round(ratio - lag(ratio) over (order by chunk_id), 6) + 0.0 as d_ratio, k - lag(k) over (order by chunk_id) as d_k from s")
def imbalance_series_events(spark, d):
    e = _t(spark, d, "events").select(F.datediff("ts", F.lit("2024-01-01")).cast("long").alias("chunk_id"), F.col("event_type").alias("cluster"))
    return metrics.imbalance_series(e).select("chunk_id", r(F.col("ratio")).alias("ratio"), "k", r(F.col("d_ratio")).alias("d_ratio"), "d_k")


@query("with b as (select min(l_quantity) a0, max(l_quantity) a1, min(l_extendedprice) b0, max(l_extendedprice) b1, min(l_discount) c0, max(l_discount) c1, min(l_tax) d0, max(l_tax) d1 from lineitem) select l_orderkey, l_linenumber, round((l_quantity-a0)/(a1-a0), 6) + 0.0 as x0, round((l_extendedprice-b0)/(b1-b0), 6) + 0.0 as x1, round((l_discount-c0)/(c1-c0), 6) + 0.0 as x2, round((l_tax-d0)/(d1-d0), 6) + 0.0 as x3 from lineitem, b")
def minmax_lineitem(spark, d):
    li = _t(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.array(*[F.col(c).cast("double") for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax")]).alias("x"))
    return features.minmax(li).select("l_orderkey", "l_linenumber", *[r(F.element_at("x", i + 1)).alias(f"x{i}") for i in range(4)])


@query("select event_id, round(case when max(value) over w > min(value) over w then (value - min(value) over w) / (max(value) over w - min(value) over w) else 0 end, 6) + 0.0 as x0 from events window w as (partition by event_id % 50)")
def minmax_events_by_chunk(spark, d):
    e = _t(spark, d, "events").select((F.col("event_id") % 50).alias("chunk_id"), "event_id", F.array("value").alias("x"))
    return features.minmax(e, ["chunk_id"]).select("event_id", r(F.element_at("x", 1)).alias("x0"))


@query("select doc_id, length(text) as length, length(text) - length(replace(text, chr(10), '')) + 1 as lines, length(text) - length(translate(text, '0123456789', '')) as digits from documents")
def text_features_documents(spark, d):
    return _t(spark, d, "documents").select("doc_id", F.length("text").cast("long").alias("length"), (F.regexp_count("text", F.lit("\\n")) + 1).cast("long").alias("lines"), F.regexp_count("text", F.lit("[0-9]")).cast("long").alias("digits"))


@query("select event_id, dense_rank() over (order by event_type) as code, cast(props->>'$.k' as bigint) as k from events")
def ordinal_codes_events(spark, d):
    kinds = _t(spark, d, "events").select("event_type").distinct().withColumn("code", F.dense_rank().over(Window.orderBy("event_type")).cast("long"))
    return _t(spark, d, "events").join(F.broadcast(kinds), "event_type").select("event_id", "code", F.get_json_object("props", "$.k").cast("long").alias("k"))


# --- Map operators ------------------------------------------------------------

_EMB = "with e as (select vec_id, list_transform(embedding, lambda v: v::double) x, label from embeddings), s as (select vec_id sid, x w from e where vec_id < 15)"


def _seeds(spark, d):
    """Codebook: the 15 lowest ids, three to a subnet, strained by id."""
    e = _emb(spark, d).where("obj_id < 15")
    return e.select(F.col("obj_id").alias("neuron"), F.col("x").alias("w"), F.floor(F.col("obj_id") / 3).alias("subnet"), ((F.col("obj_id") * 7) % 15).cast("double").alias("strain"))


def _seed_edges(spark, d):
    pairs = spark.range(5).select(F.explode(F.array(*[F.struct((F.col("id") * 3 + a).alias("a"), (F.col("id") * 3 + b).alias("b")) for a, b in ((0, 1), (0, 2), (1, 2))])).alias("e"))
    return pairs.select("e.a", "e.b")


_EDGES_SQL = "edges as (select 3*i + a as a, 3*i + b as b from range(5) t(i), (values (0,1),(0,2),(1,2)) v(a,b))"


@query(_EMB + " select vec_id as obj_id, arg_min(sid, (list_distance(x, w), sid)) as neuron, round(min(list_distance(x, w)), 6) as dist from e, s group by 1")
def winner_embeddings_15(spark, d):
    won = map_frames.winners(_emb(spark, d).select("obj_id", "x"), _seeds(spark, d))
    return won.select("obj_id", "neuron", F.round("dist", 6).alias("dist"))


@query(_EMB + " select vec_id as obj_id, arg_min(sid, (list_distance(x, w), sid)) as neuron from e, s group by 1")
def winner_sql_embeddings(spark, d):
    return map_frames.winners_sql(_emb(spark, d), _seeds(spark, d)).select("obj_id", "neuron")


@query(_EMB + ", v as (select x from e where vec_id = 15), p as (select sid from s, v order by list_distance(x, w), sid limit 1), m as (select s.sid, s.w, v.x, case when s.sid = p.sid then 0.6 when s.sid // 3 = p.sid // 3 then 0.02 else 0 end::double as rate from s, v, p) select sid as neuron, round(list_sum(list_transform(list_zip(w, x), lambda z: z[1] + rate * (z[2] - z[1]))), 6) as w_sum from m")
def step_pull_embeddings(spark, d):
    """One object's pull on the winner and its neighbours, as a plan."""
    book = _seeds(spark, d)
    v = _emb(spark, d).where("obj_id = 15").select("x")
    win = book.crossJoin(F.broadcast(v)).orderBy(features.sq_dist(F.col("x"), F.col("w")), "neuron").limit(1).select(F.col("neuron").alias("p"), F.col("subnet").alias("ps"))
    rate = F.when(F.col("neuron") == F.col("p"), 0.6).when(F.col("subnet") == F.col("ps"), 0.02).otherwise(0.0)
    moved = book.crossJoin(F.broadcast(v)).crossJoin(F.broadcast(win)).withColumn("rate", rate)
    moved = moved.withColumn("w", F.zip_with("w", "x", lambda a, b: a + F.col("rate") * (b - a)))
    return moved.select("neuron", F.round(F.aggregate("w", F.lit(0.0), lambda a, b: a + b), 6).alias("w_sum"))


@query(_EMB + ", v as (select x from e where vec_id = 15), p as (select sid, list_distance(x, w) dd from s, v order by 2, 1 limit 1) select s.sid as neuron, round(case when s.sid = p.sid then (s.sid * 7) % 15 + dd when s.sid // 3 = p.sid // 3 then ((s.sid * 7) % 15) * 0.995::double else (s.sid * 7) % 15 end, 6) as strain from s, p")
def step_strain_embeddings(spark, d):
    """Strain after one object: the winner's grows, its subnet's decays."""
    book = _seeds(spark, d)
    v = _emb(spark, d).where("obj_id = 15").select("x")
    win = book.crossJoin(F.broadcast(v)).select("neuron", "subnet", features.dist(F.col("x"), F.col("w")).alias("dd")).orderBy("dd", "neuron").limit(1).select(F.col("neuron").alias("p"), F.col("subnet").alias("ps"), "dd")
    s = F.col("strain")
    new = F.when(F.col("neuron") == F.col("p"), s + F.col("dd")).when(F.col("subnet") == F.col("ps"), s * 0.995).otherwise(s)
    return book.crossJoin(F.broadcast(win)).select("neuron", F.round(new, 6).alias("strain"))


@query("with s as (select sid, (sid * 7) % 15 strain, sid // 3 subnet from range(15) t(sid)), v as (select * from s order by strain desc, sid limit 1) select v.sid as v, (select s.sid from s where s.subnet <> v.subnet order by strain desc, sid limit 1) as g from v")
def strained_pair(spark, d):
    return map_frames.strained_pair(_seeds(spark, d))


@query(_EMB + ", " + _EDGES_SQL + ", n as (select s.*, (sid * 7) % 15 strain, sid // 3 subnet from s), v as (select * from n order by strain desc, sid limit 1), g as (select n.* from n, v where n.subnet <> v.subnet order by n.strain desc, n.sid limit 1), q as (select n.sid, list_distance(n.w, v.w) dq from n, v where n.subnet = v.subnet and n.sid <> v.sid order by dq desc, n.sid limit 1) select v.sid as v, g.sid as g, q.sid as q, list_distance(v.w, g.w) > dq as split from v, g, q")
def split_test(spark, d):
    return map_frames.split_test(_seeds(spark, d), _seed_edges(spark, d))


@query(_EMB + ", " + _EDGES_SQL + ", b as (select a, b from edges union all select b, a from edges) select b.a as neuron, round(avg(list_distance(l.w, r.w)), 6) as spread from b join s l on l.sid = b.a join s r on r.sid = b.b group by 1")
def spread_edges(spark, d):
    return map_frames.spreads(_seeds(spark, d), _seed_edges(spark, d)).select("neuron", F.round("spread", 6).alias("spread"))


# --- Gaps, merging, separability -----------------------------------------------


@query("select l_returnflag as cell, count(*) as n, round(sum(l_quantity), 4) as s0, round(sum(l_quantity * l_discount), 4) as s02, round(sum(l_tax * l_tax), 4) as s33 from lineitem group by 1")
def cell_stats_lineitem(spark, d):
    c = map_frames.cell_sums(_lineitem(spark, d), ["label"], 4)
    return c.select(F.col("label").alias("cell"), "n", F.round(F.element_at("s1", 1), 4).alias("s0"), F.round(F.element_at("s2", 3), 4).alias("s02"), F.round(F.element_at("s2", 10), 4).alias("s33"))


_PAIR = "with e as (select event_type label, value a, hour(ts)::double b, cast(props->>'$.k' as double) k from events), c as (select label, avg(a) ca, avg(b) cb, avg(k) ck from e group by 1), l as (select i.label i, j.label j, i.ca a1, i.cb b1, i.ck k1, j.ca a2, j.cb b2, j.ck k2 from c i join c j on i.label < j.label), u as (select l.i, l.j, e.label, ((a-(a1+a2)/2)*(a1-a2)+(b-(b1+b2)/2)*(b1-b2)+(k-(k1+k2)/2)*(k1-k2))/((a1-a2)*(a1-a2)+(b1-b2)*(b1-b2)+(k1-k2)*(k1-k2)) u from e join l on e.label = l.i or e.label = l.j), p as (select i, j, count(*) filter (where label = i) n_i, greatest(var_pop(u) filter (where label = i), 1e-6) v_i, count(*) filter (where label = j) n_j, greatest(var_pop(u) filter (where label = j), 1e-6) v_j from u group by 1, 2)"
_MIX = "(n_i/(n_i+n_j)*exp(-0.5*pow(s/100.0::double-0.5::double,2)/v_i)/sqrt(6.283185307179586::double*v_i) + n_j/(n_i+n_j)*exp(-0.5*pow(s/100.0::double+0.5::double,2)/v_j)/sqrt(6.283185307179586::double*v_j))"


@query(_PAIR + " select i, j, n_i, n_j, round(v_i, 4) as v_i, round(v_j, 4) as v_j from p")
def project_pairs_events(spark, d):
    return map_frames.cluster_pairs(_events(spark, d)).select("i", "j", "n_i", "n_j", F.round("v_i", 4).alias("v_i"), F.round("v_j", 4).alias("v_j"))


_QTY = "q as (select l_quantity v, count(*)::double n from lineitem group by 1)"
_MOMENTS = "sum(n) n, sum(n*v)/sum(n) c, sum(n*v*v)/sum(n) - (sum(n*v)/sum(n))*(sum(n*v)/sum(n)) e"
_SIDES = "i.n n_i, greatest(i.e/((i.c-j.c)*(i.c-j.c)), 1e-6) v_i, j.n n_j, greatest(j.e/((i.c-j.c)*(i.c-j.c)), 1e-6) v_j"
_HX = f"(with {_QTY}, b as (select floor((v-1)/10)::int b, {_MOMENTS} from q group by 1) select i.b || '-' || j.b as pair, {_SIDES} from b i join b j on i.b < j.b) p"


def _quantities(spark, d):
    """v, n: quantities of lineitem and their rows; their sums are whole numbers."""
    return _t(spark, d, "lineitem").groupBy(F.col("l_quantity").alias("v")).agg(F.count("*").alias("n"))


def _moments():
    n, c = F.sum("n"), F.sum(F.col("n") * F.col("v")) / F.sum("n")
    return n.alias("n"), c.alias("c"), (F.sum(F.col("n") * F.col("v") * F.col("v")) / n - c * c).alias("e")


def _sides():
    w2 = (F.col("i.c") - F.col("j.c")) * (F.col("i.c") - F.col("j.c"))
    return [c for s in "ij" for c in (F.col(f"{s}.n").alias(f"n_{s}"), F.greatest(F.col(f"{s}.e") / w2, F.lit(1e-6)).alias(f"v_{s}"))]


def _hx(spark, d):
    """Pairs of the five bands of quantity, along that one axis."""
    b = _quantities(spark, d).groupBy(F.floor((F.col("v") - 1) / 10).cast("int").alias("b")).agg(*_moments())
    return b.alias("i").join(b.alias("j"), F.col("i.b") < F.col("j.b")).select(F.concat_ws("-", "i.b", "j.b").alias("pair"), *_sides())


@query(f"select pair, cast(s as integer) as step, round({_MIX}, 8) as m from {_HX}, range(-50, 51) t(s)")
def mixture_curve(spark, d):
    return map_frames.mixture_curve(_hx(spark, d)).select("pair", "step", F.round("m", 8).alias("m"))


@query(_PAIR + f" select i || '-' || j as pair, round(-ln(min({_MIX})), 4) as log_gap from p, range(-50, 51) t(s) group by 1")
def log_gap_events_types(spark, d):
    return map_frames.log_gaps(map_frames.cluster_pairs(_events(spark, d))).select("pair", F.round("log_gap", 4).alias("log_gap"))


@query(f"select pair, round(-ln(min({_MIX})), 6) as log_gap from {_HX}, range(-50, 51) t(s) group by 1")
def gap_udf(spark, d):
    """The same gap through the Arrow function that SQL users get."""
    return _hx(spark, d).select("pair", F.round(sql_functions.gap_log("n_i", "v_i", "n_j", "v_j"), 6).alias("log_gap"))


@query(_PAIR + f" select round(min(g), 4) as log_theta from (select i, j, -ln(min({_MIX})) g from p, range(-50, 51) t(s) group by 1, 2)")
def compactness_events(spark, d):
    return map_frames.log_gaps(map_frames.cluster_pairs(_events(spark, d))).agg(F.round(F.min("log_gap"), 4).alias("log_theta"))


_KNN = "with e as (select vec_id, list_transform(embedding, lambda v: v::double) x, label from embeddings where vec_id < 400), n as (select a.vec_id i, b.vec_id j, a.label la, b.label lb, row_number() over (partition by a.vec_id order by list_sum(list_transform(list_zip(a.x, b.x), lambda z: (z[1]-z[2])*(z[1]-z[2]))), b.vec_id) r from e a join e b on a.vec_id <> b.vec_id qualify r <= 10)"


_KNN_ALL = _KNN.replace(" where vec_id < 400", "")


def _near(spark, d, whole: bool = False):
    """Ten nearest vectors: of the id range that the SQL names, or of all."""
    e = _emb(spark, d)
    return map_frames.knn(e if whole else e.where("obj_id < 400"), 10, 4)


def _nbr_sums(near):
    return near.groupBy("obj_id").agg(F.sum("nbr_id").cast("decimal(38,0)").alias("nbr_sum"), F.count("*").alias("n")).withColumn("nbr_sum", F.col("nbr_sum").cast("long"))


def _label_cross(spark, d, near):
    return map_frames.cross_counts(near, _emb(spark, d).select("obj_id", F.col("label").alias("cell")))


@query(_KNN + " select i as obj_id, sum(j) as nbr_sum, count(*) as n from n group by 1")
def knn10_embeddings(spark, d):
    return _nbr_sums(_near(spark, d))


@query(_KNN_ALL + " select i as obj_id, sum(j) as nbr_sum, count(*) as n from n group by 1")
def knn10_embeddings_all(spark, d):
    return _nbr_sums(_near(spark, d, whole=True))


@query(_KNN + " select la as cell_a, lb as cell_b, count(*) as c from n group by 1, 2")
def cell_cross_counts(spark, d):
    return _label_cross(spark, d, _near(spark, d))


@query(_KNN_ALL + " select la as cell_a, lb as cell_b, count(*) as c from n group by 1, 2")
def cell_cross_counts_all(spark, d):
    return _label_cross(spark, d, _near(spark, d, whole=True))


@query(_KNN + " select max(f) / 10.0::double as omega from (select la, count(*) f from n where la <> lb group by 1)")
def omega_embeddings_labels(spark, d):
    return map_frames.omega(_label_cross(spark, d, _near(spark, d)), 10)


@query(_KNN_ALL + " select max(f) / 10.0::double as omega from (select la, count(*) f from n where la <> lb group by 1)")
def omega_embeddings_labels_all(spark, d):
    return map_frames.omega(_label_cross(spark, d, _near(spark, d, whole=True)), 10)


_BAND = "floor({} * k / 50)"
_TRACE = (
    f"(with {_QTY}, o as (select k, {_BAND.format('(v-1)')}::int b, v, n, case when v > 1 and {_BAND.format('(v-2)')} <> {_BAND.format('(v-1)')} then 1 else 0 end + case when v < 50 and {_BAND.format('v')} <> {_BAND.format('(v-1)')} then 1 else 0 end f from q, range(1, 7) t(k)), "
    f"b as (select k, b, {_MOMENTS}, sum(n*f) f from o group by 1, 2), p as (select i.k, i.b, {_SIDES} from b i join b j on i.k = j.k and j.b = i.b + 1), "
    f"g as (select k, min(g) log_theta from (select k, b, -ln(min({_MIX})) g from p, range(-50, 51) t(s) group by 1, 2) group by 1), w as (select k, max(f) / 10.0::double omega from b group by 1) "
    "select w.k::int k, log_theta, omega from w left join g using (k))"
)


def _trace(spark, d):
    """k, log_theta, omega when quantity is cut into k equal bands, six to one: the
    least gap of two bands that adjoin, and the worst band's number of next
    quantities that lie in another band, counted by row, over ten."""
    v, band = F.col("v"), lambda c: F.floor(c * F.col("k") / 50).cast("int")
    o = _quantities(spark, d).withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(6)))).withColumn("b", band(v - 1))
    f = F.when((v > 1) & (band(v - 2) != F.col("b")), 1).otherwise(0) + F.when((v < 50) & (band(v) != F.col("b")), 1).otherwise(0)
    b = o.withColumn("f", f).groupBy("k", "b").agg(*_moments(), F.sum(F.col("n") * F.col("f")).alias("f"))
    near = b.alias("i").join(b.alias("j"), (F.col("i.k") == F.col("j.k")) & (F.col("j.b") == F.col("i.b") + 1))
    gaps = map_frames.log_gaps(near.select(F.struct("i.k", "i.b").alias("pair"), *_sides())).groupBy(F.col("pair.k").alias("k")).agg(F.min("log_gap").alias("log_theta"))
    worst = b.groupBy("k").agg((F.max("f") / F.lit(10.0)).alias("omega"))
    return worst.join(gaps, "k", "left").select("k", "log_theta", "omega")


def _scored(spark, d):
    t = _trace(spark, d)
    w = Window.orderBy(F.desc("k")).rowsBetween(Window.unboundedPreceding, -1)
    formed = t.withColumn("formed", F.max("log_theta").over(w))
    top = t.agg(F.max("log_theta").alias("top"), F.max("omega").alias("worst"))
    return formed.where("k >= 2").crossJoin(F.broadcast(top)).select("k", (F.coalesce(F.exp(F.col("formed") - F.col("top")), F.lit(0.0)) + F.col("omega") / F.col("worst")).alias("score"))


_SCORE = f"with s as (select k, omega, max(log_theta) over (order by k desc rows between unbounded preceding and 1 preceding) f, max(log_theta) over () top, max(omega) over () worst from {_TRACE}), q as (select k, coalesce(exp(f - top), 0) + omega / worst as score from s where k >= 2)"


@query(_SCORE + " select k, round(score, 6) as score from q")
def score_trace(spark, d):
    return _scored(spark, d).select("k", F.round("score", 6).alias("score"))


@query(_SCORE + " select arg_min(k, (score, k)) as k_hat from q")
def best_k(spark, d):
    return _scored(spark, d).agg(F.min_by("k", F.struct("score", "k")).alias("k_hat"))


@query(_SCORE + ", e as (select min(k) k0, max(k) k1, arg_min(score, k) s0, arg_max(score, k) s1 from q) select arg_max(k, (s0 + (s1 - s0) * (k - k0) / (k1 - k0) - score, -k)) as k_knee from q, e")
def knee_k(spark, d):
    q = _scored(spark, d)
    e = q.agg(F.min("k").alias("k0"), F.max("k").alias("k1"), F.min_by("score", "k").alias("s0"), F.max_by("score", "k").alias("s1"))
    below = F.col("s0") + (F.col("s1") - F.col("s0")) * (F.col("k") - F.col("k0")) / (F.col("k1") - F.col("k0")) - F.col("score")
    return q.crossJoin(F.broadcast(e)).agg(F.max_by("k", F.struct(below.alias("b"), -F.col("k"))).alias("k_knee"))


# --- Sampler and planted mixtures ------------------------------------------------

_H = "((((((({c} + 1) % 2147483648) * 1103515245 + 12345) % 2147483648 + {i} * 7919) % 2147483648 * 1103515245 + 12345) % 2147483648 + 104729) % 2147483648 * 1103515245 + 12345) % 2147483648"
_PLAN = f"with src as (select label, source_n, row_number() over (order by source_n, label) pos from (select event_type label, count(*) source_n from events group by 1)), ks as (select count(*) k_star from src), ch as (select c as chunk_id, least(2 + {_H.format(c='c', i='0')} % greatest(k_star - 1, 1), k_star) k from range(12) t(c), ks), rt as (select chunk_id, k, list_sort([1 + {_H.format(c='chunk_id', i='i')} % 5 for i in range(1, greatest(k - 1, 1) + 1)]) ratios from ch), rows as (select chunk_id, label, pos, source_n, case when pos = 1 then 1 else ratios[pos - 1] end ratio from rt join src on pos <= k)"


def _typed(spark, d):
    return _events(spark, d).select("obj_id", "x", "label")


@query(_PLAN + " select chunk_id, label, pos, source_n, ratio, case when pos = 1 then source_n else least(ratio * lag(source_n) over (partition by chunk_id order by pos), source_n) end as target_n from rows")
def sampler_plan_literal(spark, d):
    return sampler.plan(_typed(spark, d), 12, 5)


@query(_PLAN.replace("with src", "with recursive src") + ", f as (select chunk_id, label, pos, source_n, ratio, source_n as target_n from rows where pos = 1 union all select r.chunk_id, r.label, r.pos, r.source_n, r.ratio, least(f.target_n * r.ratio, r.source_n) from rows r join f on r.chunk_id = f.chunk_id and r.pos = f.pos + 1) select * from f")
def sampler_plan_chained(spark, d):
    return sampler.plan(_typed(spark, d), 12, 5, base="chunk")


_DRAWN = _PLAN + ", pl as (select chunk_id, label, case when pos = 1 then source_n else least(ratio * lag(source_n) over (partition by chunk_id order by pos), source_n) end as target_n from rows), pick as (select chunk_id, event_id as obj_id, event_type as label, row_number() over (partition by chunk_id, label order by " + _H.format(c="(event_id + chunk_id * 31)", i="3") + ", event_id) rn, target_n from events join pl on event_type = label)"


@query(_DRAWN + " select chunk_id, label, count(*) as n, sum(obj_id)::bigint as ids from pick where rn <= target_n group by 1, 2")
def sampler_draw_events(spark, d):
    pts = _typed(spark, d)
    return sampler.draw(pts, sampler.plan(pts, 12, 5)).groupBy("chunk_id", "label").agg(F.count("*").alias("n"), F.sum("obj_id").alias("ids"))


@query(_DRAWN.replace("range(12)", "range(50)").replace("% 5 for", "% 2 for") + ", n as (select chunk_id, label, count(*) n from pick where rn <= target_n group by 1, 2) select chunk_id, round(max(n) / min(n), 6) as ratio, count(*) as k from n group by 1")
def sampler_stream_50(spark, d):
    s = sampler.stream(_typed(spark, d), 50, 2)
    return metrics.imbalance(s, ["chunk_id"], "label").select("chunk_id", F.round("ratio", 6).alias("ratio"), "k")


def _planted_sql(name: str, whole: bool = False) -> str:
    source, key, spread, clusters = planted.SPECS[name]
    lcg = lambda v: f"(({v}) % 2147483648 * 1103515245 + 12345) % 2147483648"
    u1 = f"greatest({lcg(lcg(lcg('k * 2 + 5')))} / 2147483648.0::double, 1e-9)"
    u2 = f"{lcg(lcg(lcg('k * 2 + 16') + ' + 77'))} / 2147483648.0::double"
    cases = lambda j: "case " + " ".join(f"when place < {sum(c[2] for c in clusters[: i + 1])} then {c[j] if j < 2 else i}" for i, c in enumerate(clusters)) + " end"
    where = " where o_orderkey < 3200" if source == "orders" and not whole else ""
    place = lcg(lcg("k + 17")) + " % 1000"
    day = "date_diff('day', date '2024-01-01', cast(ts as date))" if name == "drift" else "0"
    turned = f"case when day < 15 then {place} else 999 - {place} end"
    return (
        f"with k as (select {key} k, {day} as day from {source}{where}), p as (select k, day, {turned} place, {u1} u1, {u2} u2 from k) "
        f"select cast({'day' if name == 'drift' else '0'} as bigint) as chunk_id, k as obj_id, round({cases(0)} + {'day * 0.01::double' if name == 'drift' else '0'} + {spread}::double * sqrt(-2.0 * ln(u1)) * cos(6.283185307179586 * u2), 6) + 0.0 as x0, "
        f"round({cases(1)} + {spread}::double * sqrt(-2.0 * ln(u1)) * sin(6.283185307179586 * u2), 6) + 0.0 as x1, {cases(2)} as label from p"
    )


def _planted(name: str, below: int = 0):
    """The mixture as rows; with below, those ids only, as its SQL has them."""
    def run(spark, d):
        m = planted.mixture(spark, d, name)
        return (m.where(F.col("obj_id") < below) if below else m).select("chunk_id", "obj_id", r(F.element_at("x", 1)).alias("x0"), r(F.element_at("x", 2)).alias("x1"), "label")

    return run


for _name, _key, _below in (("ga", "planted_ga_part", 0), ("id", "planted_id_orders", 3200), ("drift", "planted_drift_events", 0)):
    query(_planted_sql(_name), _key)(_planted(_name, _below))
query(_planted_sql("id", whole=True), "planted_id_orders_all")(_planted("id"))

# --- Measures ----------------------------------------------------------------------

_C = "with c as (select l_returnflag label, l_linestatus cluster, count(*)::double n from lineitem group by 1, 2), a as (select label, sum(n) m from c group by 1), b as (select cluster, sum(n) m from c group by 1), t as (select sum(n) t from c)"


@query("select l_returnflag as label, l_linestatus as cluster, count(*) as n from lineitem group by 1, 2")
def contingency(spark, d):
    return metrics.contingency(_lineitem(spark, d))


@query(_C + ", s as (select (select sum(n*(n-1)/2) from c) x, (select sum(m*(m-1)/2) from a) r, (select sum(m*(m-1)/2) from b) k, t*(t-1)/2 p from t) select round((x - r*k/p) / ((r+k)/2 - r*k/p), 9) + 0.0 as ari from s")
def ari(spark, d):
    return metrics.ari(_lineitem(spark, d)).select(r(F.col("ari"), 9).alias("ari"))


def _nmi(norm: str, below: str):
    sql = _C + f", s as (select (select sum(n/t * ln(n*t/(a.m*b.m))) from c join a using (label) join b using (cluster)) i, (select -sum(m/t*ln(m/t)) from a) hl, (select -sum(m/t*ln(m/t)) from b) hc from t) select round(i / {below}, 9) + 0.0 as nmi from s"
    query(sql, f"nmi_{norm}")(lambda spark, d: metrics.nmi(_lineitem(spark, d), norm=norm).select(r(F.col("nmi"), 9).alias("nmi")))


for _norm, _below in (("arith", "((hl+hc)/2)"), ("sqrt", "sqrt(hl*hc)"), ("min", "least(hl,hc)"), ("max", "greatest(hl,hc)")):
    _nmi(_norm, _below)


@query("with c as (select l_returnflag g, avg(l_quantity) a, avg(l_extendedprice) b, avg(l_discount) c, avg(l_tax) e from lineitem group by 1), s as (select g, any_value(a) a, any_value(b) b, any_value(c) c, any_value(e) e, avg(sqrt((l_quantity-a)*(l_quantity-a)+(l_extendedprice-b)*(l_extendedprice-b)+(l_discount-c)*(l_discount-c)+(l_tax-e)*(l_tax-e))) s from lineitem join c on l_returnflag = g group by 1) select round(avg(w), 2) as dbi from (select l.g, max((l.s+r.s)/sqrt((l.a-r.a)*(l.a-r.a)+(l.b-r.b)*(l.b-r.b)+(l.c-r.c)*(l.c-r.c)+(l.e-r.e)*(l.e-r.e))) w from s l join s r on l.g <> r.g group by 1)")
def dbi(spark, d):
    return metrics.dbi(_lineitem(spark, d).withColumn("cluster", F.col("label"))).select(F.round("dbi", 2).alias("dbi"))


@query("select count(distinct l_linestatus) as k_hat, count(distinct l_returnflag) as k_true, count(distinct l_linestatus) - count(distinct l_returnflag) as k_error, count(distinct l_linestatus) = 1 as one_cluster from lineitem")
def k_error(spark, d):
    return metrics.k_error(_lineitem(spark, d))


@query("with c as (select l_returnflag l, l_linestatus, count(*) n from lineitem group by 1, 2), s as (select l, sum(n) t, max(n) m from c group by 1) select round(arg_min(m / t, (t, l)), 6) as minority_recall from s")
def minority_recall(spark, d):
    return metrics.minority_recall(_lineitem(spark, d)).select(F.round("minority_recall", 6).alias("minority_recall"))


_RES = "(select event_type as dataset, 'm' || (user_id % 4) as method, case event_id % 2 when 0 then 'ari' else 'dbi' end as measure, event_id as chunk_id, value from events)"


def _results(spark, d):
    """Values of the event table as if they were results of four methods."""
    e = _t(spark, d, "events")
    return e.select(F.col("event_type").alias("dataset"), F.concat(F.lit("m"), F.col("user_id") % 4).alias("method"), F.when(F.col("event_id") % 2 == 0, "ari").otherwise("dbi").alias("measure"), F.col("event_id").alias("chunk_id"), "value")


@query(f"select dataset, method, measure, round(avg(value), 6) as mean, round(stddev_samp(value), 6) as deviation, count(value) as chunks from {_RES} group by 1, 2, 3")
def summary_mean_std(spark, d):
    return metrics.summary(_results(spark, d)).select("dataset", "method", "measure", F.round("mean", 6).alias("mean"), F.round("deviation", 6).alias("deviation"), "chunks")


@query(f"with m as (select dataset, method, measure, avg(value) v from {_RES} group by 1, 2, 3), p as (select method, rank() over (partition by dataset, measure order by case measure when 'dbi' then v else -v end) place from m) select method, count(*) filter (where place = 1) as first, count(*) filter (where place = 2) as second from p group by 1")
def rank_methods(spark, d):
    return metrics.rank_table(_results(spark, d))


@query("select n, q, d, n*q as winner_distances, n*5 as pulls, n // 100 as structural_steps, n*q*q*4*d as intra_merging, n*15*15*15*d as inter_merging, n*n*q*d + n*q*10 as separability_objects, q*q*q*d + q*q*10 as separability_neurons, n*q*q*d as total_time, n*d + n*q as total_space from (select n, q, 8::bigint as d from (select count(*) as n from events group by time_bucket(interval '864 minutes', ts, timestamp '2024-01-01')) a, (values (20::bigint), (60)) b(q))")
def cost_predict(spark, d):
    """Costs of each true-time chunk of the event stream, for two sizes of map."""
    n = chunks.by_time(_t(spark, d, "events")).groupBy("chunk_id").agg(F.count("*").alias("n"))
    sizes = n.select("n", F.explode(F.array(F.lit(20).cast("long"), F.lit(60).cast("long"))).alias("q"), F.lit(8).cast("long").alias("d"))
    return metrics.predicted_costs(sizes)


# --- Baselines that SQL can follow ---------------------------------------------------

_KM = "with e as (select event_id i, value a, hour(ts)::double b from events), c0 as (select i k, a, b from e where i < 3)"
for _r in range(3):
    _KM += f", a{_r} as (select e.i, arg_min(k, ((e.a-c.a)*(e.a-c.a)+(e.b-c.b)*(e.b-c.b), k)) k from e, c{_r} c group by 1), c{_r + 1} as (select k, avg(a) a, avg(b) b from e join a{_r} using (i) group by 1)"


def _plane(spark, d):
    return _events(spark, d).select("obj_id", F.array(F.element_at("x", 1), F.element_at("x", 2)).alias("x"))


def _three(spark, d):
    return _plane(spark, d).where("obj_id < 3").select(F.col("obj_id").alias("cluster"), F.col("x").alias("centre"))


@query(_KM + " select k as cluster, round(a, 6) as c0, round(b, 6) as c1 from c3")
def kmeans_3rounds_events(spark, d):
    c = map_frames.kmeans_rounds(_plane(spark, d), _three(spark, d), 3)
    return c.select("cluster", F.round(F.element_at("centre", 1), 6).alias("c0"), F.round(F.element_at("centre", 2), 6).alias("c1"))


@query(_KM + " select k as cluster, count(*) as n from a2 group by 1")
def kmeans_assign(spark, d):
    c = map_frames.kmeans_rounds(_plane(spark, d), _three(spark, d), 2)
    won = map_frames.winners(_plane(spark, d), c.select(F.col("cluster").alias("neuron"), F.col("centre").alias("w")))
    return won.groupBy(F.col("neuron").alias("cluster")).agg(F.count("*").alias("n"))


_DPC = "with e as (select vec_id i, list_transform(embedding, lambda v: v::double) x from embeddings where vec_id < 300), p as (select a.i, b.i j, list_sum(list_transform(list_zip(a.x, b.x), lambda z: (z[1]-z[2])*(z[1]-z[2]))) d2 from e a join e b on a.i <> b.i), r as (select i, count(*) filter (where d2 < 1.7) rho from p group by 1)"


_DPC_ALL = _DPC.replace(" where vec_id < 300", "")


def _vectors(spark, d, below: int = 0):
    """Vectors; with below, of those ids only."""
    e = _emb(spark, d)
    return e.where(F.col("obj_id") < below) if below else e


def _rho(e):
    return map_frames.within(e, 1.7, 4)


@query(_DPC + " select i as obj_id, rho from r")
def dpc_density_embeddings(spark, d):
    return _rho(_vectors(spark, d, 300))


@query(_DPC_ALL + " select i as obj_id, rho from r")
def dpc_density_embeddings_all(spark, d):
    return _rho(_vectors(spark, d))


def _delta(e):
    """Nearest denser vector of each, and its distance."""
    return map_frames.nearest_denser(e, _rho(e), 4).select("obj_id", "parent", F.round(F.sqrt("d2"), 6).alias("delta"))


@query(_DPC + " select p.i as obj_id, arg_min(p.j, (d2, p.j)) as parent, round(sqrt(min(d2)), 6) as delta from p join r a on a.i = p.i join r b on b.i = p.j where b.rho > a.rho or (b.rho = a.rho and p.j < p.i) group by 1")
def dpc_delta_embeddings(spark, d):
    return _delta(_vectors(spark, d, 300))


@query(_DPC_ALL + " select p.i as obj_id, arg_min(p.j, (d2, p.j)) as parent, round(sqrt(min(d2)), 6) as delta from p join r a on a.i = p.i join r b on b.i = p.j where b.rho > a.rho or (b.rho = a.rho and p.j < p.i) group by 1")
def dpc_delta_embeddings_all(spark, d):
    return _delta(_vectors(spark, d))


def _fknn(spark, d, near):
    e = _emb(spark, d)
    near = near.join(e.select("obj_id", "x"), "obj_id").join(e.select(F.col("obj_id").alias("nbr_id"), F.col("x").alias("y")), "nbr_id")
    return near.groupBy("obj_id").agg(F.round(F.sum(F.exp(-features.dist(F.col("x"), F.col("y")))), 6).alias("density"))


@query(_KNN.replace("la, b.label lb,", "la, b.label lb, list_sum(list_transform(list_zip(a.x, b.x), lambda z: (z[1]-z[2])*(z[1]-z[2]))) d2,") + " select i as obj_id, round(sum(exp(-sqrt(d2))), 6) as density from n group by 1")
def fknn_density(spark, d):
    return _fknn(spark, d, _near(spark, d))


@query(_KNN_ALL.replace("la, b.label lb,", "la, b.label lb, list_sum(list_transform(list_zip(a.x, b.x), lambda z: (z[1]-z[2])*(z[1]-z[2]))) d2,") + " select i as obj_id, round(sum(exp(-sqrt(d2))), 6) as density from n group by 1")
def fknn_density_all(spark, d):
    return _fknn(spark, d, _near(spark, d, whole=True))


@query("with e as (select event_id i, value a, hour(ts)::double b from events), c as (select i m, a, b from e where i < 6), w as (select e.i, arg_min(m, ((e.a-c.a)*(e.a-c.a)+(e.b-c.b)*(e.b-c.b), m)) m from e, c group by 1), s as (select m, sum(a) sa, sum(b) sb, count(*) n from e join w using (i) group by 1), h as (select c.m as neuron, s.*, exp(-(pow(c.m // 3 - s.m // 3, 2) + pow(c.m % 3 - s.m % 3, 2)) / 2.0) h from c, s) select neuron, round(sum(h * sa) / sum(h * n), 6) as w0, round(sum(h * sb) / sum(h * n), 6) as w1 from h group by 1")
def som_round(spark, d):
    book = _plane(spark, d).where("obj_id < 6").select(F.col("obj_id").alias("neuron"), F.col("x").alias("w"))
    s = map_frames.som_round(_plane(spark, d), book, 1.0, 3)
    return s.groupBy("neuron").agg(F.round(F.max(F.when(F.col("pos") == 0, F.col("w"))), 6).alias("w0"), F.round(F.max(F.when(F.col("pos") == 1, F.col("w"))), 6).alias("w1"))


@query("select event_type as cell, count(*) as n, round(sum(value), 4) as ls, round(sum(value * value), 2) as ss from events group by 1")
def cf_sums(spark, d):
    """Cluster features add up: count, linear and square sums."""
    return _t(spark, d, "events").groupBy(F.col("event_type").alias("cell")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("ls"), F.round(F.sum(F.col("value") * F.col("value")), 2).alias("ss"))


# --- The whole method, baselines, ablations, workloads (no SQL) ----------------------


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Clusters of the planted set with their sizes and the accuracy reached."""
    pts = tables.points(spark, d, "ga")
    a = pipeline.with_truth(pts, pipeline.cluster(pts)).select("label", "cluster")
    return a.groupBy("cluster").agg(F.count("*").alias("n")).crossJoin(F.broadcast(metrics.ari(a)))


query()(flagship)


@query()
def fit_ga_part(spark, d):
    pts = tables.points(spark, d, "ga")
    return experiments.measured(pts, pipeline.cluster(pts), "ga", "growing_map")


@query()
def fit_id_orders(spark, d):
    pts = tables.points(spark, d, "id")
    return experiments.measured(pts, pipeline.cluster(pts), "id", "growing_map")


@query()
def fit_neurons_ga(spark, d):
    return pipeline.neurons(tables.points(spark, d, "ga"))


@query()
def fit_edges_ga(spark, d):
    return pipeline.edges(tables.points(spark, d, "ga"))


@query()
def fit_trace_ga(spark, d):
    return pipeline.trace(tables.points(spark, d, "ga"))


@query()
def fit_counters_ga(spark, d):
    return pipeline.counters(tables.points(spark, d, "ga"))


@query()
def fit_fixed_k_ga(spark, d):
    return pipeline.cluster(tables.points(spark, d, "ga"), replace(Params(), k=3))


@query()
def fit_sharded_events(spark, d):
    return pipeline.cluster_sharded(tables.points(spark, d, "lm"), shards=8).groupBy("cluster").agg(F.count("*").alias("n"))


@query()
def predict_ga(spark, d):
    pts = tables.points(spark, d, "ga")
    return pipeline.predict(pts, pipeline.neurons(pts))


@query()
def batch_map_events(spark, d):
    pts = tables.points(spark, d, "lm")
    return pipeline.batch_codebook(pts, pts.where("obj_id < 15").select(F.col("obj_id").alias("neuron"), F.col("x").alias("w")), rounds=3)


@query()
def fit_warm_drift(spark, d):
    pts = tables.points(spark, d, "drift")
    return pipeline.cluster_in_order(pts, Params(carry="warm", prune="idle"))


@query()
def fit_windows_events(spark, d):
    """Fifty true-time chunks of the event stream."""
    pts = tables.points(spark, d, "lm").drop("chunk_id").join(chunks.by_time(_t(spark, d, "events")).select(F.col("event_id").alias("obj_id"), "chunk_id"), "obj_id")
    return experiments.measured(pts, pipeline.cluster_chunks(pts), "lm", "growing_map")


def _baseline(method: str):
    def run(spark, d):
        pts = tables.points(spark, d, "ga")
        return experiments.measured(pts, experiments.run_method(pts, method, 4), "ga", method)

    return run


for _m in METHODS:
    query(name=f"baseline_{_m}")(_baseline(_m))


def _ablate(variant: str):
    def run(spark, d):
        pts = tables.points(spark, d, "ga")
        return experiments.measured(pts, pipeline.cluster(pts, replace(Params(), **experiments.ABLATIONS[variant])), "ga", variant)

    return run


for _v in experiments.ABLATIONS:
    query(name=f"ablate_{_v}")(_ablate(_v))


@query()
def workload_accuracy(spark, d):
    """All sets, all named methods, ten chunks each."""
    return metrics.summary(experiments.accuracy(spark, d, list(tables.SETS)))


@query()
def workload_ranks(spark, d):
    return metrics.rank_table(experiments.accuracy(spark, d, list(tables.SETS)))


@query()
def workload_ablation(spark, d):
    return experiments.ablation(spark, d, list(tables.SETS))


@query()
def workload_efficiency(spark, d):
    return spark.createDataFrame(experiments.efficiency(spark, d), "method string, n long, seconds double")


@query()
def workload_streaming(spark, d):
    return experiments.streaming_series(spark, d, chunks=50)


@query()
def workload_failures(spark, d):
    return experiments.failures(spark, d)


@query()
def workload_drift(spark, d):
    return metrics.summary(experiments.drift(spark, d))


@query()
def workload_parameters(spark, d):
    return experiments.parameter_grid(spark, d)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    from . import surrounding

    return dict(_QUERIES) | surrounding.queries()


def oracle_sql() -> dict[str, str]:
    from . import surrounding

    return dict(_SQL) | surrounding.oracle_sql()
