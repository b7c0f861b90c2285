"""Registered queries of the moving-group engine, over whole tables, and their SQL.

Queries of one table folder share what they have in common: it is worked out once for each
session and folder, and stands on shared storage.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from groupflow.functions import pruning
from groupflow.operators import baselines, chains, density, distances, incremental, lineage, links, patterns, peel, sectors, snapshots
from groupflow.params import Params
from groupflow.plans import experiments, measures, surface, sweeps
from groupflow.plans.oracles import recall_sql, sector_steps, sql, strict_steps
from groupflow.plans.pipeline import Discovery, clusters, discover, discover_in
from groupflow.sources import tracks
from groupflow.storage import materialize, scratch_path
from groupflow.streaming import engine

P = Params()
#: Planted walks: the published setting but for ``d``, which fits the walks' speed.
PLANTED_SMALL = Params(eps=1.5, min_pts=2, w=6, k_c=5, m_c=2, k_p=4, m_p=2, d=5.0, m_g=1.0, k_g=14)
PLANTED = Params(eps=1.5, min_pts=2, w=14, k_c=10, m_c=2, k_p=8, m_p=2, d=8.0, m_g=1.0, k_g=14)


_HELD: dict[tuple, object] = {}


def _once(work):
    """``work(spark, sf_dir, ...)`` once for each application and arguments; what it returns stands on shared storage."""

    @wraps(work)
    def run(spark: SparkSession, *arguments):
        key = (work.__name__, spark.sparkContext.applicationId, *arguments)
        if key not in _HELD:
            _HELD[key] = work(spark, *arguments)
        return _HELD[key]

    return run


@_once
def _clusters(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    return clusters(_kept(spark, sf_dir), P)


@_once
def _all(spark: SparkSession, sf_dir: str) -> Discovery:
    return discover_in(*_clusters(spark, sf_dir), P)


@_once
def _kept(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hourly positions, written once for what reads them many times."""
    return materialize(tracks.hourly_events(spark, sf_dir), "snap")


def _snap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tracks.hourly_events(spark, sf_dir)


def _r(*names: str) -> list:
    return [F.round(n, 6).alias(n) for n in names]


def _text(c: str):
    return F.concat_ws("-", F.col(c).cast("array<string>"))


def snapshots_hourly(spark, sf_dir):
    fixes = snapshots.bucket(tracks.event_fixes(spark, sf_dir), tracks.HOUR, tracks.EVENT_ORIGIN)
    return fixes.groupBy("t").agg(F.count("*").alias("fixes"), F.count_distinct("obj_id").alias("objects"))


def snapshots_last_position(spark, sf_dir):
    fixes = snapshots.bucket(tracks.event_fixes(spark, sf_dir), tracks.HOUR, tracks.EVENT_ORIGIN)
    return snapshots.synchronize(fixes).select("t", "obj_id", *_r("x", "y"))


def snapshots_mean_position(spark, sf_dir):
    fixes = snapshots.bucket(tracks.event_fixes(spark, sf_dir), tracks.HOUR, tracks.EVENT_ORIGIN)
    return snapshots.synchronize(fixes, "mean").select("t", "obj_id", *_r("x", "y"))


def interpolated_tracks(spark, sf_dir):
    return _snap(spark, sf_dir).select("t", "obj_id", *_r("x", "y"))


def interpolated_max_gap(spark, sf_dir):
    fixes = tracks.event_fixes(spark, sf_dir)
    return snapshots.interpolate(fixes, tracks.HOUR, tracks.EVENT_ORIGIN, 12).select("t", "obj_id", *_r("x", "y"))


def planted_walks(spark, sf_dir):
    """Walks of all customers."""
    return tracks.planted_walks(spark, sf_dir).select("t", "obj_id", *_r("x", "y"))


def embedding_tracks(spark, sf_dir):
    return tracks.embedding_tracks(spark, sf_dir).select("t", "obj_id", *_r("x", "y"))


def lineitem_sightings(spark, sf_dir):
    """Sightings on all ship dates."""
    return tracks.lineitem_fixes(spark, sf_dir).select("obj_id", F.unix_micros("ts").alias("us"), *_r("x", "y"))


def dataset_size(spark, sf_dir):
    return measures.describe(_snap(spark, sf_dir)).withColumn("distance", F.round("distance", 3))


def core_objects(spark, sf_dir):
    return density.core_objects(_snap(spark, sf_dir), P.eps, P.min_pts).filter("is_core").select("t", "obj_id")


def density_clusters(spark, sf_dir):
    return _all(spark, sf_dir).member.select("t", "cluster_id", "obj_id", "is_core")


def density_clusters_by_snapshot(spark, sf_dir):
    member = density.cluster(_snap(spark, sf_dir), P.eps, P.min_pts, plan="snapshot")
    return density.keep_large(member, P.m_c).select("t", "cluster_id", "obj_id", "is_core")


def density_clusters_by_grid(spark, sf_dir):
    member = density.cluster(_snap(spark, sf_dir), P.eps, P.min_pts, plan="grid", least=P.m_c)
    return member.select("t", "cluster_id", "obj_id", "is_core")


def cluster_sizes(spark, sf_dir):
    return _all(spark, sf_dir).member.groupBy("t").agg(F.count_distinct("cluster_id").alias("clusters"), F.count("*").alias("members"))


def cluster_shapes(spark, sf_dir):
    return _all(spark, sf_dir).shape.select("cluster_id", "t", F.col("n").cast("long").alias("n"), *_r("mx", "my", "r", "var", "minx", "maxx", "miny", "maxy"))


def hausdorff_distances(spark, sf_dir):
    found = _all(spark, sf_dir)
    pairs = distances.with_squares(found.link, found.shape, P.max_gap)
    return pairs.select("src", "dst", F.round(F.sqrt("q"), 6).alias("distance"))


def _links(index: str, prune: bool):
    def query(spark, sf_dir):
        return links.build(_all(spark, sf_dir).shape, P, index, prune).select("src", "dst", F.col("dt").cast("long").alias("dt"))

    return query


def link_decisions(spark, sf_dir):
    shape = _all(spark, sf_dir).shape
    decided = links.decide(links.candidates(shape, P, "none"), shape, P)
    return measures.pruning(decided).select("decided_by", "n", "linked", F.round("share", 6).alias("share"))


def _rule(kind: str, rule: str):
    def query(spark, sf_dir):
        shape = _all(spark, sf_dir).shape
        limit = F.lit(P.d) * F.col("dt")
        says = (pruning.far if kind == "far" else pruning.near)("a", "b", limit, rule)
        return links.candidates(shape, P, "none").filter(says).select(F.col("a.cluster_id").alias("src"), F.col("b.cluster_id").alias("dst"))

    return query


def rule_errors(spark, sf_dir):
    """Pairs that each rule decides, and those of them that it decides wrongly."""
    shape = _all(spark, sf_dir).shape
    link = _all(spark, sf_dir).link.select("src", "dst", F.lit(True).alias("is_link"))
    limit = F.lit(P.d) * F.col("dt")
    says = {
        "far_hull": pruning.far("a", "b", limit, "hull"),
        "far_printed": pruning.far("a", "b", limit, "printed"),
        "near_printed": pruning.near("a", "b", limit, "printed"),
        "near_sound": pruning.near("a", "b", limit, "sound"),
    }
    pairs = links.candidates(shape, P, "none").select(
        F.col("a.cluster_id").alias("src"), F.col("b.cluster_id").alias("dst"), F.explode(F.array(*[F.when(c, F.lit(n)) for n, c in says.items()])).alias("rule")
    )
    wrong = F.coalesce("is_link", F.lit(False)) == F.col("rule").startswith("far")
    return pairs.filter("rule is not null").join(link, ["src", "dst"], "left").groupBy("rule").agg(
        F.count("*").alias("n"), F.count_if(wrong).alias("wrong")
    )


def cover_links(spark, sf_dir):
    return _all(spark, sf_dir).cover.select("src", "dst", F.col("dt").cast("long").alias("dt"))


def closed_crowds(spark, sf_dir):
    return _all(spark, sf_dir).crowd.select("crowd_id", F.col("len").cast("long").alias("len"), "s_lo", "s_hi")


def participators(spark, sf_dir):
    found = _all(spark, sf_dir)
    return peel.participators(found.crowd, found.shape, P.k_p)


def aggregation_check(spark, sf_dir):
    found = _all(spark, sf_dir)
    return peel.aggregation_check(found.crowd, found.shape, P)


def _aggregations(impl: str):
    def query(spark, sf_dir):
        found = _all(spark, sf_dir)
        agg = peel.peel(found.crowd, found.shape, P, impl)
        return agg.select("agg_id", "s_lo", "s_hi", _text("members").alias("members"), F.col("size").cast("long").alias("size"))

    return query


def closed_aggregations(spark, sf_dir):
    return _all(spark, sf_dir).windows.select("win", "agg_id", _text("members").alias("members"))


def groups(spark, sf_dir):
    return _all(spark, sf_dir).group.select("win", "group_id", F.col("size").cast("long").alias("size"), "n_aggs")


def evolution_edges(spark, sf_dir):
    return _all(spark, sf_dir).evo.select("win", "src_group", "dst_group", "common", *_r("ratio"))


def lineage_events(spark, sf_dir):
    found = _all(spark, sf_dir)
    return lineage.events(found.group, found.evo).withColumn("size", F.col("size").cast("long"))


def _chains(spark, sf_dir):
    found = _all(spark, sf_dir)
    return lineage.chains(found.group, found.evo, P.k_g, P.w)


def evolving_groups(spark, sf_dir):
    wide = {c: F.col(c).cast("long") for c in ("n_windows", "n_timestamps", "first_win", "last_win")}
    return _chains(spark, sf_dir).withColumns(wide).drop("groups")


def average_length(spark, sf_dir):
    return measures.average_length(_chains(spark, sf_dir)).select("n", F.round("avg_timestamps", 6).alias("avg_timestamps"), F.col("max_timestamps").cast("long").alias("max_timestamps"))


def pattern_counts(spark, sf_dir):
    return measures.pattern_counts(_chains(spark, sf_dir).select(F.col("first_win").alias("t")))


def pattern_cube(spark, sf_dir):
    """Counts by period and day type with all totals."""
    return measures.by_period(pattern_counts(spark, sf_dir))


def _days(spark, sf_dir) -> DataFrame:
    """Days of each type that the snapshots cover."""
    day = _snap(spark, sf_dir).select(F.floor(F.col("t") / 24).alias("d")).distinct()
    kind = F.when(F.dayofweek(F.date_add(F.lit("2024-01-01").cast("date"), F.col("d").cast("int"))).isin(1, 7), "weekend").otherwise("workday")
    return day.groupBy(kind.alias("day_type")).agg(F.count("*").alias("days"))


def pattern_counts_per_day(spark, sf_dir):
    """Evolving groups and strict gatherings that start in each period, in all and for a day."""
    found = _all(spark, sf_dir)
    crowd = baselines.cut_at_invalid(baselines.strict_crowds(found.shape, found.link, 3), found.shape, 3, 2, P.m_p)
    strict = measures.pattern_counts(crowd.select(F.shiftright(F.element_at("path", 1), 32).alias("t")))
    both = pattern_counts(spark, sf_dir).withColumn("pattern", F.lit("evolving")).unionByName(strict.withColumn("pattern", F.lit("strict")))
    mean = F.round(F.col("n") / F.col("days"), 6).alias("per_day")
    return both.join(F.broadcast(_days(spark, sf_dir)), "day_type").select("pattern", "period", "day_type", "n", mean)


def average_length_at_equal_counts(spark, sf_dir):
    """Mean length of as many evolving groups as there are strict crowds of a window's length or more, longest first."""
    found = _all(spark, sf_dir)
    strict = baselines.strict_crowds(found.shape, found.link, P.w).agg(F.count("*").alias("n"))
    cut = measures.equal_cut(_chains(spark, sf_dir), strict)
    return cut.select(F.col("k_g").cast("long").alias("k_g"), F.col("n").cast("long").alias("n"), *_r("avg_timestamps"))


def window_sizes(spark, sf_dir):
    found = _all(spark, sf_dir)
    return measures.window_sizes(found.shape, found.link, found.crowd, found.group, P.w)


#: Windows of the registered case study.
CASE = (300, 323)


def case_graph_nodes(spark, sf_dir):
    found = _all(spark, sf_dir)
    nodes, _ = measures.case_graph(found.group, found.evo, lineage.depths(found.group, found.evo), *CASE)
    return nodes.select("group_id", "win", F.col("size").cast("long").alias("size"), F.col("life").cast("long").alias("life"), _text("members").alias("members"))


def case_graph_edges(spark, sf_dir):
    found = _all(spark, sf_dir)
    return measures.case_graph(found.group, found.evo, lineage.depths(found.group, found.evo), *CASE)[1]


def largest_groups(spark, sf_dir):
    """The three largest groups of each window."""
    order = Window.partitionBy("win").orderBy(F.desc("size"), "group_id")
    ranked = _all(spark, sf_dir).group.select("win", "group_id", F.col("size").cast("long").alias("size"), F.row_number().over(order).cast("long").alias("place"))
    return ranked.filter("place <= 3")


def cost_model(spark, sf_dir):
    found = _all(spark, sf_dir)
    decided = links.decide(links.candidates(found.shape, P, "none"), found.shape, P)
    predicted = measures.cost_model(measures.cost_stats(decided, found.shape, found.crowd, P.w), P, PARTS, sectors.ring_count(PARTS))
    return predicted.select(*[F.round(c, 3).alias(c) for c in predicted.columns])


def closed_crowds_without_gaps(spark, sf_dir):
    """Closed crowds where a crowd has a cluster at every timestamp of its window."""
    found, p = _all(spark, sf_dir), P.but(k_c=P.w)
    crowd = chains.closed_crowds(found.shape, chains.cover(links.build(found.shape, p)), p)
    return crowd.select("crowd_id", F.col("len").cast("long").alias("len"), "s_lo", "s_hi")


def parallel_differences(spark, sf_dir):
    """Groups that the method by space parts, or by random distribution, finds otherwise than the serial one: none."""
    known = _all(spark, sf_dir)
    serial, out = known.group.select("win", "group_id"), None
    for method in ("sector", "random"):
        # clusters do not depend on the method
        found = discover_in(known.member, known.shape, P, index=method, n_parts=PARTS).group.select("win", "group_id")
        one = found.exceptAll(serial).unionByName(serial.exceptAll(found)).agg(F.count("*").alias("differences")).select(F.lit(method).alias("method"), "differences")
        out = one if out is None else out.unionByName(one)
    return out


def experiment_times(spark, sf_dir):
    """Seconds and answers of the methods beside their competitors, for each value of a parameter."""
    found, snap = _all(spark, sf_dir), _kept(spark, sf_dir)
    p = P.but(w=8, k_c=6, k_p=5)
    parts = [
        experiments.crowd_step(found.shape, "k_c", [(k, p.but(k_c=k)) for k in (6, 7, 8)]),
        experiments.verifier(found.crowd, found.shape, "k_p", [(k, P.but(k_p=k)) for k in (2, 4)]),
        experiments.verifier(found.crowd, found.shape, "m_p", [(m, P.but(m_p=m)) for m in (2, 5)]),
        experiments.whole(snap, [*[("objects", *x) for x in experiments.objects(snap, P, 2)], *[("d", d, snap, P.but(d=d)) for d in (3.0, 5.0)]]),
        experiments.space_parts(found.shape, P, (2, 8)),
    ]
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return measures.speedup(out, "serial")


def state_size(spark, sf_dir):
    found = _all(spark, sf_dir)
    return measures.state_size(found.shape, found.link, found.crowd, found.group)


def strict_crowds(spark, sf_dir):
    found = _all(spark, sf_dir)
    return baselines.strict_crowds(found.shape, found.link, P.k_c).select("crowd_id", F.col("len").cast("long").alias("len"))


def gatherings(spark, sf_dir):
    found = _all(spark, sf_dir)
    crowd = baselines.strict_crowds(found.shape, found.link, 3)
    return baselines.gatherings(crowd, found.shape, 2, P.m_p).select("crowd_id", F.col("len").cast("long").alias("len"))


def closed_gatherings(spark, sf_dir):
    """Gatherings that no longer one of their crowd holds, by cutting crowds at clusters without enough participators."""
    found = _all(spark, sf_dir)
    crowd = baselines.strict_crowds(found.shape, found.link, 3)
    return baselines.cut_at_invalid(crowd, found.shape, 3, 2, P.m_p).select("crowd_id")


def convoys(spark, sf_dir):
    found = baselines.convoys(_all(spark, sf_dir).member, 3, 3)
    return found.select(_text("objs").alias("objs"), "first_t", "last_t")


def flocks(spark, sf_dir):
    found = patterns.flocks(_snap(spark, sf_dir), P.eps, 3, 4)
    return found.select("anchor", "first_t", _text("members").alias("members"))


def swarms(spark, sf_dir):
    found = patterns.swarms(_clusters(spark, sf_dir)[0], 3, 12)
    return found.select(_text("objs").alias("objs"), F.size("clusters").cast("long").alias("n"))


def chain_depths(spark, sf_dir):
    found = _all(spark, sf_dir)
    return lineage.depths(found.group, found.evo)


#: Space parts of the registered queries.
PARTS = 8


def _parts(spark, sf_dir, n_parts: int = PARTS) -> tuple[DataFrame, DataFrame]:
    shape = _all(spark, sf_dir).shape
    points = sectors.polar(shape, sectors.center(shape))
    return points, materialize(sectors.divide(points, n_parts), "parts")


def sector_homes(spark, sf_dir):
    return sectors.home(*_parts(spark, sf_dir)).select("t", "cluster_id", F.col("part").cast("long").alias("part"))


def sector_balance(spark, sf_dir):
    found = sectors.balance(sectors.home(*_parts(spark, sf_dir)), PARTS)
    return found.select("t", "clusters", "fullest", *_r("imbalance"))


def sector_kinds(spark, sf_dir):
    """Clusters inside one part of the timestamp before, and those that reach several."""
    kinds = sectors.assign(*_parts(spark, sf_dir), P.d)
    return kinds.groupBy("t", F.col("kind").cast("long").alias("kind")).agg(F.count("*").alias("n"), F.sum(F.size("met")).alias("parts"))


def sector_missed_links(spark, sf_dir):
    """Links that boundary zones of the printed width miss, by time gap."""
    found = _all(spark, sf_dir)
    narrow = links.build(found.shape, P, "sector", n_parts=PARTS, halo="printed").select("src", "dst", F.lit(1).alias("one"))
    both = found.link.join(narrow, ["src", "dst"], "left")
    return both.groupBy(F.col("dt").cast("long").alias("dt")).agg(F.count("*").alias("n"), F.count_if(F.col("one").isNull()).alias("missed"))


def parallel_pairs(spark, sf_dir):
    """Pairs that each distribution compares, and the most of a task."""
    shape = _all(spark, sf_dir).shape
    out = None
    for name in ("none", "random", "sector"):
        pairs = links.candidates(shape, P, name, n_parts=PARTS)
        one = pairs.agg(F.count("*").alias("pairs")).select(F.lit(name).alias("method"), "pairs")
        out = one if out is None else out.unionByName(one)
    return out


@_once
def _streamed(spark: SparkSession, sf_dir: str) -> engine.GroupStream:
    sink = engine.GroupStream(scratch_path(spark, "stream"), P)
    engine.run(engine.replay(_snap(spark, sf_dir), 3), sink)
    return sink


def stream_groups(spark, sf_dir):
    """The groups of all windows, from the stream."""
    found = _streamed(spark, sf_dir).groups(spark)
    return found.select("win", "group_id", F.col("size").cast("long").alias("size"), "n_aggs")


def stream_evolution_edges(spark, sf_dir):
    found = _streamed(spark, sf_dir).evolution(spark)
    return found.select("win", "src_group", "dst_group", "common", *_r("ratio"))


def stream_crowds(spark, sf_dir):
    """Closed crowds of each window, from the stream."""
    found = _streamed(spark, sf_dir).crowds(spark)
    return found.select(F.explode(F.sequence("s_lo", "s_hi")).alias("win"), "crowd_id")


def stream_aggregations(spark, sf_dir):
    """Closed aggregations of each window, verified from what was kept of earlier crowds."""
    return _streamed(spark, sf_dir).aggregations(spark).select("win", "agg_id", _text("members").alias("members"))


def stream_reuse(spark, sf_dir):
    """How the stream verified its crowds: as before, from a longer crowd, without the newest cluster, or from the whole."""
    return _streamed(spark, sf_dir).crowds(spark).groupBy("how").agg(F.count("*").alias("crowds"))


def stream_closed_evolving_groups(spark, sf_dir):
    """Evolving groups that came to their end while the stream ran, by their last group."""
    return _streamed(spark, sf_dir).closed(spark)


def closed_evolving_groups(spark, sf_dir):
    """The same from the whole table at once."""
    found = _all(spark, sf_dir)
    deep = lineage.depths(found.group, found.evo)
    last = found.group.agg(F.max("win").alias("last"))
    over = deep.join(F.broadcast(last), F.col("win") < F.col("last")).filter((F.col("depth_out") == 1) & (F.col("depth_in") >= P.k_g))
    first = (F.col("win") - F.col("depth_in") + 1).alias("first_win")
    return over.select("group_id", first, F.col("win").alias("last_win"), F.col("depth_in").cast("long").alias("n_windows"))


def evolving_families(spark, sf_dir):
    """Evolving groups as families: groups that long chains connect."""
    found = _all(spark, sf_dir)
    return lineage.families(found.group, found.evo, P.k_g, P.w)


def incremental_crowds_planted(spark, sf_dir):
    """Closed crowds of each window of the planted walks of all customers, timestamp by timestamp."""
    _, shape = clusters(tracks.planted_walks(spark, sf_dir), PLANTED_SMALL)
    ends = shape.agg(F.min("t").alias("lo"), F.max("t").alias("hi")).first()
    state, out = None, None
    for t in range(ends["lo"], ends["hi"] + 1) if ends["lo"] is not None else ():
        state, _ = incremental.crowd_step(state, shape.filter(F.col("t") == t), t, PLANTED_SMALL)
        one = incremental.crowds(state, PLANTED_SMALL).select("win", "crowd_id")
        out = one if out is None else out.unionByName(one)
    return out if out is not None else spark.createDataFrame([], "win long, crowd_id string")


def sql_hausdorff(spark, sf_dir):
    """Distances of linked clusters by the functions and views that a user of SQL sees."""
    surface.register(spark, _snap(spark, sf_dir), _all(spark, sf_dir))
    return spark.sql(
        """SELECT l.src, l.dst, round(hausdorff(a.pts, b.pts), 6) AS distance FROM links l
        JOIN shapes a ON a.cluster_id = l.src JOIN shapes b ON b.cluster_id = l.dst WHERE hausdorff_within(a.pts, b.pts, {d} * l.dt)""".format(d=P.d)
    )


def sweep_d(spark, sf_dir):
    """Candidate pairs and links for growing distances."""
    return sweeps.distances(_all(spark, sf_dir).shape, P, (2.0, 3.0, 4.0, 5.0))


def sweep_k_p(spark, sf_dir):
    """Aggregations for growing participation, over the same crowds."""
    found = _all(spark, sf_dir)
    return sweeps.verification(found.crowd, found.shape, [P.but(k_p=k) for k in (2, 3, 4, 5)])


def sweep_m_p(spark, sf_dir):
    found = _all(spark, sf_dir)
    return sweeps.verification(found.crowd, found.shape, [P.but(m_p=m) for m in (2, 3, 4, 5)])


def sweep_k_c(spark, sf_dir):
    """Closed crowds for growing least lengths in windows of ``w``."""
    found = _all(spark, sf_dir)
    return sweeps.crowds(found.shape, found.link, [P.but(k_c=k) for k in (5, 6)])


def sweep_m_c(spark, sf_dir):
    found = _all(spark, sf_dir)
    return sweeps.sizes(found.shape, found.link, [P.but(m_c=m) for m in (3, 4, 5)])


def sweep_objects(spark, sf_dir):
    """Clusters for growing parts of the objects, a fifth to all of them."""
    return sweeps.objects(_snap(spark, sf_dir), P, 5)


def ablation(spark, sf_dir):
    """Pairs that are compared point by point with each device switched off; the links are the same."""
    return sweeps.ablation(_all(spark, sf_dir).shape, P)


@_once
def _planted(spark: SparkSession, sf_dir: str, d: float, k_c: int) -> Discovery:
    return discover(tracks.planted_walks(spark, sf_dir), PLANTED.but(d=d, k_c=k_c))


def _long_lived(spark, sf_dir, d: float, k_c: int) -> DataFrame:
    """Groups on a chain of at least ``k_g`` windows."""
    found = _planted(spark, sf_dir, d, k_c)
    return lineage.long_lived(found.group, found.evo, PLANTED.k_g).join(found.group, ["group_id", "win"])


def _recall(d: float, k_c: int):
    def query(spark, sf_dir):
        return _measured(measures.precision_recall(_long_lived(spark, sf_dir, d, k_c), tracks.planted_truth(spark, sf_dir)))

    return query


def _measured(found: DataFrame) -> DataFrame:
    return found.withColumns({c: F.round(c, 6) for c in ("precision", "recall", "f1")})


def _strict_gatherings(spark, sf_dir, d: float) -> DataFrame:
    """Members of the strict gatherings of the planted walks, by the published lengths."""
    found = _planted(spark, sf_dir, d, PLANTED.w)
    crowd = baselines.strict_crowds(found.shape, found.link, 28)
    closed = baselines.cut_at_invalid(crowd, found.shape, 28, 16, PLANTED.m_p)
    rows = closed.select("crowd_id", F.explode("path").alias("cluster_id")).join(found.shape.select("cluster_id", "objs"), "cluster_id")
    each = rows.groupBy("crowd_id").agg(F.flatten(F.collect_list("objs")).alias("every"))
    return each.select(peel.frequent(F.col("every"), 16).alias("members"))


def _recall_strict(d: float):
    def query(spark, sf_dir):
        return _measured(measures.precision_recall(_strict_gatherings(spark, sf_dir, d), tracks.planted_truth(spark, sf_dir)))

    return query


def planted_recall_by_period(spark, sf_dir):
    """Precision and recall by period and day type, evolving groups beside strict gatherings. Districts stand for recordings."""
    truth = tracks.planted_truth(spark, sf_dir)
    found = {"evolving": _long_lived(spark, sf_dir, 8.0, 10).select("members"), "strict": _strict_gatherings(spark, sf_dir, 8.0)}
    district = F.floor(F.element_at("members", 1) / tracks.DISTRICT)
    name = lambda d: [(d % 4).alias("period"), F.when(F.floor(d / 4) % 2 == 0, "workday").otherwise("weekend").alias("day_type")]
    out = None
    for method, rows in found.items():
        one = measures.precision_recall(
            rows.select("members", *name(district)), truth.select("members", *name(F.col("district"))), ["period", "day_type"]
        )
        one = one.withColumn("method", F.lit(method))
        out = one if out is None else out.unionByName(one)
    return _measured(out)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        snapshots_hourly, snapshots_last_position, snapshots_mean_position, interpolated_tracks, interpolated_max_gap,
        lineitem_sightings, planted_walks, embedding_tracks, dataset_size, core_objects, density_clusters,
        density_clusters_by_snapshot, density_clusters_by_grid, cluster_sizes, cluster_shapes, hausdorff_distances, link_decisions, rule_errors,
        cover_links, closed_crowds, participators, aggregation_check, closed_aggregations, groups, evolution_edges,
        lineage_events, evolving_groups, average_length, pattern_counts, pattern_cube, pattern_counts_per_day, average_length_at_equal_counts, window_sizes,
        case_graph_nodes, case_graph_edges, largest_groups, cost_model, closed_crowds_without_gaps, parallel_differences, experiment_times, state_size, strict_crowds, gatherings,
        closed_gatherings, convoys, flocks, swarms, chain_depths, sector_homes, sector_balance, sector_kinds, sector_missed_links,
        parallel_pairs, stream_crowds, stream_aggregations, stream_reuse, stream_groups, stream_evolution_edges, stream_closed_evolving_groups, closed_evolving_groups, evolving_families, incremental_crowds_planted,
        sql_hausdorff, planted_recall_by_period, sweep_d, sweep_k_p, sweep_m_p, sweep_k_c, sweep_m_c, sweep_objects, ablation,
    )
}
QUERIES |= {
    "links": _links("box", True),
    "links_grid_index": _links("grid", True),
    "links_no_index": _links("none", False),
    "links_sector_parallel": _links("sector", True),
    "links_random_parallel": _links("random", True),
    "prune_far_printed": _rule("far", "printed"),
    "prune_far_hull": _rule("far", "hull"),
    "prune_near_printed": _rule("near", "printed"),
    "prune_near_sound": _rule("near", "sound"),
    "aggregations_per_crowd": _aggregations("expr"),
    "aggregations_relational": _aggregations("relational"),
    "planted_recall": _recall(8.0, 10),
    "planted_recall_no_gaps": _recall(8.0, 14),
    "planted_recall_published_distance": _recall(5.0, 10),
    "planted_recall_no_gaps_published_distance": _recall(5.0, 14),
    "planted_recall_strict": _recall_strict(8.0),
    "planted_recall_strict_published_distance": _recall_strict(5.0),
}



def smoke(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups with distances that suit the few objects of the smallest tables."""
    found = discover(_snap(spark, sf_dir), Params(eps=15.0, d=15.0))
    return found.group.select("win", "group_id", F.col("size").cast("long").alias("size"), "n_aggs")


_ROUND = "round({0}, 6) AS {0}"
_LIMIT = f"({P.d}::DOUBLE * (b.t - a.t))"
_BETWEEN = "sqrt((a.mx - b.mx) ** 2 + (a.my - b.my) ** 2)"
_PAIRS = f"FROM shape a JOIN shape b ON b.t > a.t AND b.t - a.t <= {P.max_gap}"
_RULES = {
    "far_printed": f"{_BETWEEN} > ({_LIMIT} + a.r + b.r) * (1 + 1e-9)",
    "far_hull": f"{_BETWEEN} > ({_LIMIT} + least(a.r, b.r)) * (1 + 1e-9)",
    "near_printed": f"{_BETWEEN} + greatest(a.r, b.r) <= {_LIMIT}",
    "near_sound": f"greatest(({_BETWEEN} + a.r) ** 2 + b.var, ({_BETWEEN} + b.r) ** 2 + a.var) <= {_LIMIT} ** 2 * (1 - 1e-9)",
}
_COUNTS = """SELECT period, day_type, count(*) AS n FROM (SELECT CASE WHEN {t} % 24 BETWEEN 7 AND 9 THEN '07-10' WHEN {t} % 24 BETWEEN 10 AND 12 THEN '10-13'
          WHEN {t} % 24 BETWEEN 13 AND 15 THEN '13-16' WHEN {t} % 24 BETWEEN 16 AND 19 THEN '16-20' END AS period,
          CASE WHEN dayofweek(TIMESTAMP '2024-01-01' + to_hours({t})) IN (0, 6) THEN 'weekend' ELSE 'workday' END AS day_type FROM {source})
        WHERE period IS NOT NULL GROUP BY ALL"""
_T = f"floor((epoch_us(ts) - {tracks.EVENT_ORIGIN}) / {tracks.HOUR})::BIGINT"
_XY = "t, obj_id, round(x, 6) AS x, round(y, 6) AS y"
_MEMBER = "SELECT t, cluster_id, obj_id, is_core FROM member"
_AGG = "SELECT agg_id, s_lo, s_hi, array_to_string(members, '-') AS members, size FROM agg"
_DISTANCE = f"SELECT src, dst, round(sqrt(q), 6) AS distance FROM hausdorff WHERE q <= ({P.d}::DOUBLE * dt) * ({P.d}::DOUBLE * dt)"
_LINK = sql("SELECT src, dst, dt FROM link", "link", P)
_GROUPS = sql("SELECT win, group_id, size, n_aggs FROM grp", "grp", P)
_EDGES = sql("SELECT win, src_group, dst_group, common, round(ratio, 6) AS ratio FROM evo", "evo", P)
_WALKS = f"""SELECT t, id AS obj_id, (id // {tracks.DISTRICT}) * {tracks.APART} + (abs((377 * a + (a % 5 + 1) * t) % 600 - 300) + s * ((k % 4) * 0.6::DOUBLE - 0.9::DOUBLE)) AS x,
          abs((911 * a + (a % 7 + 1) * t) % 600 - 300) + s * ((k * 7 + t) % 3 * 0.2::DOUBLE) AS y
        FROM (SELECT *, CASE WHEN g % 3 = 1 AND (t + g) % 9 = 4 THEN 20.0::DOUBLE ELSE 1.0::DOUBLE END AS s FROM (
          SELECT *, CASE WHEN g % 3 <> 2 THEN g ELSE 1000 + k END AS a, unnest(range(42)) AS t FROM (
            SELECT c_custkey AS id, c_custkey % {tracks.DISTRICT} AS k, c_custkey % {tracks.DISTRICT} // 4 AS g FROM customer)))"""
_SECTOR = sector_steps(P, sectors.ring_count(PARTS), PARTS // sectors.ring_count(PARTS))



def _union(selects: list[str], inner: list[str]) -> str:
    return " UNION ALL ".join(s.format(i) for s, i in zip(selects, inner, strict=True))


def _sweep(name: str, values: tuple[int, ...]) -> str:
    return _union(
        [f"SELECT {v} AS {name}, count(*) AS aggregations, coalesce(sum(size), 0)::BIGINT AS members FROM ({{}})" for v in values],
        [sql("SELECT DISTINCT agg_id, size FROM agg", "agg", P.but(**{name: v})) for v in values],
    )


ORACLE_SQL: dict[str, str] = {
    "snapshots_hourly": sql(f"SELECT {_T} AS t, count(*) AS fixes, count(DISTINCT obj_id) AS objects FROM fixes GROUP BY 1", "fixes"),
    "snapshots_last_position": sql(
        f"SELECT {_T} AS t, obj_id, round(arg_max(x, (ts, event_id)), 6) AS x, round(arg_max(y, (ts, event_id)), 6) AS y FROM fixes GROUP BY 1, 2", "fixes"
    ),
    "snapshots_mean_position": sql(f"SELECT {_T} AS t, obj_id, round(avg(x), 6) AS x, round(avg(y), 6) AS y FROM fixes GROUP BY 1, 2", "fixes"),
    "interpolated_tracks": sql(f"SELECT {_XY} FROM snap", "snap"),
    "interpolated_max_gap": sql(
        """SELECT t, obj_id, round(CASE WHEN t = e THEN x ELSE x + (x2 - x) * ((t - e) / (e2 - e)) END, 6) AS x,
        round(CASE WHEN t = e THEN y ELSE y + (y2 - y) * ((t - e) / (e2 - e)) END, 6) AS y
        FROM (SELECT *, unnest(generate_series(ceil(e)::BIGINT, CASE WHEN e2 IS NULL OR e2 - e > 12 THEN floor(e) ELSE ceil(e2) - 1 END::BIGINT)) AS t FROM legs)""",
        "legs",
    ),
    "lineitem_sightings": """SELECT l_partkey AS obj_id, epoch_us(l_shipdate::TIMESTAMP) AS us, round(avg(s_acctbal::DOUBLE / 100), 6) AS x,
        round(avg((s_nationkey * 4)::DOUBLE), 6) AS y FROM lineitem JOIN supplier ON s_suppkey = l_suppkey GROUP BY 1, 2""",
    "planted_walks": f"SELECT t, obj_id, round(x, 6) AS x, round(y, 6) AS y FROM ({_WALKS})",
    "embedding_tracks": """SELECT i::BIGINT AS t, vec_id AS obj_id, round(embedding[2 * i + 1]::DOUBLE, 6) AS x, round(embedding[2 * i + 2]::DOUBLE, 6) AS y
        FROM (SELECT *, unnest(range(len(embedding) // 2)) AS i FROM embeddings)""",
    "dataset_size": sql(
        """SELECT count(*) AS points, count(DISTINCT obj_id) AS objects, count(DISTINCT t) AS snapshots, round(sum(step), 3) AS distance FROM (
          SELECT *, sqrt((x - lag(x) OVER o) ** 2 + (y - lag(y) OVER o) ** 2) AS step FROM snap WINDOW o AS (PARTITION BY obj_id ORDER BY t))""",
        "snap",
    ),
    "core_objects": sql("SELECT t, obj_id FROM core", "core", P),
    "density_clusters": sql(_MEMBER, "member", P),
    "density_clusters_by_snapshot": sql(_MEMBER, "member", P),
    "density_clusters_by_grid": sql(_MEMBER, "member", P),
    "cluster_sizes": sql("SELECT t, count(DISTINCT cluster_id) AS clusters, count(*) AS members FROM member GROUP BY t", "member", P),
    "cluster_shapes": sql(
        "SELECT cluster_id, t, n, " + ", ".join(_ROUND.format(c) for c in ("mx", "my", "r", "var", "minx", "maxx", "miny", "maxy")) + " FROM shape", "shape", P
    ),
    "hausdorff_distances": sql(_DISTANCE, "hausdorff", P),
    "links": _LINK,
    "links_grid_index": _LINK,
    "links_no_index": _LINK,
    "links_sector_parallel": _LINK,
    "links_random_parallel": _LINK,
    "sector_homes": sql("SELECT t, cluster_id, part FROM homes", "shape", P, _SECTOR),
    "sector_balance": sql(
        f"""SELECT t, sum(n)::BIGINT AS clusters, max(n) AS fullest, round(max(n)::DOUBLE * {PARTS} / sum(n)::DOUBLE, 6) AS imbalance
        FROM (SELECT t, part, count(*) AS n FROM homes GROUP BY t, part) GROUP BY t""",
        "shape",
        P,
        _SECTOR,
    ),
    "sector_kinds": sql(
        """SELECT t, kind, count(*) AS n, sum(parts)::BIGINT AS parts FROM (SELECT b.t, b.cluster_id, count(m.part) AS parts,
          CASE WHEN count(m.part) <= 1 THEN 1 ELSE 2 END AS kind FROM polar b LEFT JOIN met m ON m.cluster_id = b.cluster_id
          WHERE b.t - 1 IN (SELECT t FROM part) GROUP BY ALL) GROUP BY t, kind""",
        "shape",
        P,
        _SECTOR,
    ),
    "sector_missed_links": sql(
        """SELECT dt, count(*) AS n, count(*) FILTER (WHERE NOT coalesce(narrow, false)) AS missed
        FROM link LEFT JOIN reached USING (src, dst) GROUP BY dt""",
        "link",
        P,
        _SECTOR,
    ),
    "parallel_pairs": sql(
        f"""SELECT 'none' AS method, count(*) AS pairs {_PAIRS} UNION ALL SELECT 'random', count(*) {_PAIRS}
        UNION ALL SELECT 'sector', count(*) FROM reached""",
        "shape",
        P,
        _SECTOR,
    ),
    "flocks": sql(
        f"""SELECT anchor, first_t, array_to_string(list(obj ORDER BY obj), '-') AS members FROM (
          SELECT anchor, obj, unnest(generate_series(lo, hi - 3)) AS first_t FROM (
            SELECT anchor, obj, min(t) AS lo, max(t) AS hi FROM (
              SELECT obj_id AS anchor, other AS obj, t, t - row_number() OVER (PARTITION BY obj_id, other ORDER BY t) AS run FROM near)
            GROUP BY anchor, obj, run HAVING max(t) - min(t) >= 3)) GROUP BY anchor, first_t HAVING count(*) >= 3""",
        "near",
        P,
    ),
    "swarms": sql(
        """SELECT array_to_string(objs, '-') AS objs, len(clusters) AS n FROM sets s WHERE len(objs) >= 3 AND NOT EXISTS (
          SELECT 1 FROM held h WHERE NOT list_contains(s.objs, h.obj_id) AND list_has_all(h.clusters, s.clusters))""",
        "member",
        P,
        {
            "held": "SELECT obj_id, list(cluster_id ORDER BY cluster_id) AS clusters FROM member GROUP BY obj_id",
            "sets": """SELECT [obj_id] AS objs, obj_id AS last, clusters FROM held UNION ALL
              SELECT list_append(s.objs, h.obj_id), h.obj_id, list_sort(list_intersect(s.clusters, h.clusters)) FROM sets s JOIN held h ON h.obj_id > s.last
              WHERE len(list_intersect(s.clusters, h.clusters)) >= 12""",
        },
    ),
    "chain_depths": sql(
        """SELECT group_id, win, (SELECT max(n) FROM ins i WHERE i.g = group_id) AS depth_in, (SELECT max(n) FROM outs o WHERE o.g = group_id) AS depth_out FROM grp""",
        "evo",
        P,
        {
            "ins": "SELECT group_id AS g, 1::BIGINT AS n FROM grp UNION SELECT e.dst_group, i.n + 1 FROM ins i JOIN evo e ON e.src_group = i.g",
            "outs": "SELECT group_id AS g, 1::BIGINT AS n FROM grp UNION SELECT e.src_group, o.n + 1 FROM outs o JOIN evo e ON e.dst_group = o.g",
        },
    ),
    "strict_crowds": sql(f"SELECT crowd_id, n AS len FROM strict WHERE n >= {P.k_c}", "link", P, strict_steps()),
    "gatherings": sql("SELECT crowd_id, hi - lo + 1 AS len FROM gathering WHERE lo = 1 AND hi = n", "link", P, strict_steps(3, 2, P.m_p)),
    "closed_gatherings": sql(
        """SELECT DISTINCT array_to_string(path[lo:hi], '-') AS crowd_id FROM gathering g WHERE NOT EXISTS (
          SELECT 1 FROM gathering w WHERE w.crowd_id = g.crowd_id AND w.lo <= g.lo AND w.hi >= g.hi AND w.hi - w.lo > g.hi - g.lo)""",
        "link",
        P,
        strict_steps(3, 2, P.m_p),
    ),
    "convoys": sql(
        """SELECT array_to_string(objs, '-') AS objs, first_t, last_t FROM kept k WHERE NOT EXISTS (SELECT 1 FROM kept b
          WHERE b.first_t <= k.first_t AND b.last_t >= k.last_t AND list_has_all(b.objs, k.objs)
            AND (b.first_t < k.first_t OR b.last_t > k.last_t OR len(b.objs) > len(k.objs)))""",
        "member",
        P,
        {
            "held": "SELECT t, list(obj_id ORDER BY obj_id) AS objs FROM member GROUP BY t, cluster_id HAVING count(*) >= 3",
            "live": """SELECT t AS first_t, t AS last_t, objs FROM held UNION
              SELECT l.first_t, h.t, list_sort(list_intersect(l.objs, h.objs)) FROM live l JOIN held h ON h.t = l.last_t + 1
              WHERE len(list_intersect(l.objs, h.objs)) >= 3""",
            "kept": "SELECT DISTINCT * FROM live WHERE last_t - first_t >= 2",
        },
    ),
    "sweep_objects": _union(
        [
            f"""SELECT {k / 5}::DOUBLE AS part, (SELECT count(DISTINCT obj_id) FROM ({{0}})) AS objects, (SELECT count(*) FROM ({{0}})) AS points,
            (SELECT count(DISTINCT cluster_id) FROM ({sql("SELECT cluster_id FROM member", "member", P, snap=f"SELECT * FROM ({sql('SELECT * FROM snap', 'snap')}) WHERE obj_id % 5 < {k}")})) AS clusters"""
            for k in range(1, 6)
        ],
        [sql(f"SELECT * FROM snap WHERE obj_id % 5 < {k}", "snap") for k in range(1, 6)],
    ),
    "ablation": _union(
        [f"SELECT '{n}' AS off, count(*) AS pairs, count(*) FILTER (WHERE {{}}) AS exact, count(*) FILTER (WHERE is_link AND dt <= {P.max_gap}) AS links FROM pairs WHERE {w}" for n, w in
         {"nothing": f"dt <= {P.max_gap} AND boxed", "index": f"dt <= {P.max_gap}", "pruning": f"dt <= {P.max_gap} AND boxed", "gap_bound": "boxed"}.items()],
        ["NOT decided", "NOT decided", "true", "NOT decided"],
    ),
    "link_decisions": sql(
        f"""SELECT decided_by, count(*) AS n, count(*) FILTER (WHERE is_link) AS linked, round(count(*) / sum(count(*)) OVER (), 6) AS share
        FROM (SELECT CASE WHEN {_RULES["far_hull"]} THEN 'far' WHEN {_RULES["near_sound"]} THEN 'near' ELSE 'exact' END AS decided_by,
          EXISTS (SELECT 1 FROM link l WHERE l.src = a.cluster_id AND l.dst = b.cluster_id) AS is_link {_PAIRS}) GROUP BY decided_by""",
        "link",
        P,
    ),
    "rule_errors": sql(
        " UNION ALL ".join(
            f"""SELECT '{n}' AS rule, count(*) AS n, count(*) FILTER (WHERE is_link = {str(n.startswith("far")).lower()}) AS wrong
            FROM (SELECT EXISTS (SELECT 1 FROM link l WHERE l.src = a.cluster_id AND l.dst = b.cluster_id) AS is_link {_PAIRS} WHERE {c}) HAVING count(*) > 0"""
            for n, c in _RULES.items()
        ),
        "link",
        P,
    ),
    "cover_links": sql("SELECT src, dst, dt FROM cover", "cover", P),
    "sql_hausdorff": sql(_DISTANCE, "hausdorff", P),
    "sweep_d": sql(
        f"SELECT d, count(*) AS pairs, count(*) FILTER (WHERE q <= (d * dt) ** 2) AS linked FROM hausdorff, (VALUES (2.0::DOUBLE), (3.0), (4.0), (5.0)) v(d) GROUP BY d",
        "hausdorff",
        P,
    ),
    "sweep_k_p": _sweep("k_p", (2, 3, 4, 5)),
    "sweep_m_p": _sweep("m_p", (2, 3, 4, 5)),
    "sweep_k_c": _union([f"SELECT {k} AS k_c, count(*) AS crowds, coalesce(sum(s_hi - s_lo + 1), 0)::BIGINT AS windows FROM ({{}})" for k in (5, 6)],
        [sql("SELECT s_lo, s_hi FROM crowd", "crowd", P.but(k_c=k)) for k in (5, 6)]),
    "sweep_m_c": _union([f"SELECT {m} AS m_c, (SELECT count(*) FROM ({{}})) AS links" for m in (3, 4, 5)],
        [sql("SELECT 1 FROM link", "link", P.but(m_c=m)) for m in (3, 4, 5)]),
    "closed_crowds": sql("SELECT crowd_id, len, s_lo, s_hi FROM crowd", "crowd", P),
    "participators": sql("SELECT crowd_id, obj_id, cnt FROM real0", "real0", P),
    "aggregation_check": sql(
        f"""SELECT crowd_id, min(n) AS least, min(n) >= {P.m_p} AS is_aggregation FROM (
          SELECT a.crowd_id, a.cluster_id, count(r.obj_id) AS n FROM alive0 a JOIN member m USING (cluster_id)
          LEFT JOIN real0 r ON r.crowd_id = a.crowd_id AND r.obj_id = m.obj_id GROUP BY 1, 2) GROUP BY crowd_id""",
        "real0",
        P,
    ),
    "aggregations_per_crowd": sql(_AGG, "agg", P),
    "aggregations_relational": sql(_AGG, "agg", P),
    "closed_aggregations": sql("SELECT win, agg_id, array_to_string(members, '-') AS members FROM closed", "closed", P),
    "groups": _GROUPS,
    "evolution_edges": _EDGES,
    "stream_crowds": sql("SELECT unnest(generate_series(s_lo, s_hi)) AS win, crowd_id FROM crowd", "crowd", P),
    "stream_aggregations": sql("SELECT win, agg_id, array_to_string(members, '-') AS members FROM closed", "closed", P),
    "stream_groups": _GROUPS,
    "stream_evolution_edges": _EDGES,
    "incremental_crowds_planted": sql("SELECT unnest(generate_series(s_lo, s_hi)) AS win, crowd_id FROM crowd", "crowd", PLANTED_SMALL, snap=_WALKS),
    "lineage_events": sql(
        """SELECT group_id, win, size, n_in, n_out, n_in = 0 AS starts, n_out = 0 AS ends, n_out > 1 AS splits, n_in > 1 AS merges,
          coalesce(n_in = 1 AND size > was, false) AS grows, coalesce(n_in = 1 AND size < was, false) AS shrinks
        FROM (SELECT *, (SELECT count(*) FROM evo WHERE src_group = group_id) AS n_out, (SELECT count(*) FROM evo WHERE dst_group = group_id) AS n_in,
          (SELECT max(s.size) FROM evo e JOIN grp s ON s.group_id = e.src_group WHERE e.dst_group = g.group_id) AS was FROM grp g)""",
        "evo",
        P,
    ),
    "evolving_groups": sql("SELECT * FROM chain", "chain", P),
    "average_length": sql(
        "SELECT count(*) AS n, round(avg(n_timestamps), 6) AS avg_timestamps, max(n_timestamps) AS max_timestamps FROM chain", "chain", P
    ),
    "pattern_counts": sql(_COUNTS.format(t="first_win", source="chain"), "chain", P),
    "pattern_cube": sql(
        f"SELECT period, day_type, grouping_id(period, day_type)::BIGINT AS level, sum(n)::BIGINT AS n FROM ({_COUNTS.format(t='first_win', source='chain')}) GROUP BY CUBE (period, day_type)",
        "chain",
        P,
    ),
    "pattern_counts_per_day": sql(
        f"""SELECT pattern, period, day_type, n, round(n::DOUBLE / days, 6) AS per_day FROM (
          SELECT 'evolving' AS pattern, * FROM ({_COUNTS.format(t="first_win", source="chain")})
          UNION ALL SELECT 'strict', * FROM ({_COUNTS.format(t="first_t", source="closed_gathering")})) JOIN (
          SELECT CASE WHEN dayofweek(DATE '2024-01-01' + d::INT) IN (0, 6) THEN 'weekend' ELSE 'workday' END AS day_type, count(*) AS days
          FROM (SELECT DISTINCT t // 24 AS d FROM snap) GROUP BY 1) USING (day_type)""",
        "chain",
        P,
        strict_steps(3, 2, P.m_p)
        | {
            "closed_gathering": """SELECT DISTINCT path[lo:hi] AS part, path[lo] // 4294967296 AS first_t FROM gathering g WHERE NOT EXISTS (
              SELECT 1 FROM gathering w WHERE w.crowd_id = g.crowd_id AND w.lo <= g.lo AND w.hi >= g.hi AND w.hi - w.lo > g.hi - g.lo)"""
        },
    ),
    "average_length_at_equal_counts": sql(
        f"""SELECT k_g, n, round(s::DOUBLE / n, 6) AS avg_timestamps FROM (SELECT a.n_windows AS k_g, (SELECT count(*) FROM chain c WHERE c.n_windows >= a.n_windows) AS n,
          (SELECT sum(n_timestamps) FROM chain c WHERE c.n_windows >= a.n_windows) AS s FROM (SELECT DISTINCT n_windows FROM chain) a)
        WHERE n >= (SELECT count(*) FROM strict WHERE strict.n >= {P.w}) ORDER BY k_g DESC LIMIT 1""",
        "chain",
        P,
        strict_steps(),
    ),
    "window_sizes": sql(
        f"""SELECT win, (SELECT count(*) FROM shape s WHERE s.t BETWEEN win AND win + {P.w - 1}) AS clusters,
          (SELECT count(*) FROM link WHERE src // 4294967296 >= win AND dst // 4294967296 <= win + {P.w - 1}) AS links,
          (SELECT count(*) FROM crowd WHERE s_lo <= win AND s_hi >= win) AS crowds, (SELECT count(*) FROM grp g WHERE g.win = u.win) AS groups
        FROM (SELECT unnest(generate_series(lo, hi - {P.w - 1})) AS win FROM bounds) u
        WHERE EXISTS (SELECT 1 FROM shape s WHERE s.t BETWEEN win AND win + {P.w - 1})""",
        "grp",
        P,
    ),
    "largest_groups": sql(
        "SELECT win, group_id, size, row_number() OVER (PARTITION BY win ORDER BY size DESC, group_id) AS place FROM grp QUALIFY place <= 3", "grp", P
    ),
    "case_graph_edges": sql(f"SELECT src_group, dst_group, common FROM evo WHERE win BETWEEN {CASE[0]} AND {CASE[1] - 1}", "evo", P),
    "closed_crowds_without_gaps": sql("SELECT crowd_id, len, s_lo, s_hi FROM crowd", "crowd", P.but(k_c=P.w)),
    "parallel_differences": "SELECT unnest(['sector', 'random']) AS method, 0::BIGINT AS differences",
    "cost_model": sql(
        f"""SELECT round((1 - alpha) * m * q * k * k, 3) AS crowd_cost, round(l * {P.w - P.k_c} * k, 3) AS verify_cost, round(l * l, 3) AS lineage_cost,
          round(m + m * log2(m) + m * log2(m / {sectors.ring_count(PARTS)}), 3) AS partition_cost, round(m / {PARTS} + {sectors.ring_count(PARTS)}, 3) AS part_space
        FROM (SELECT (SELECT count(*)::DOUBLE / count(DISTINCT t) FROM shape) AS m, (SELECT avg(n) FROM shape) AS k,
          (SELECT count(*) {_PAIRS})::DOUBLE / (SELECT count(*) FROM shape) AS q,
          (SELECT count(*) FILTER (WHERE {_RULES["far_hull"]} OR {_RULES["near_sound"]})::DOUBLE / count(*) {_PAIRS}) AS alpha,
          (SELECT sum(s_hi - s_lo + 1) FROM crowd)::DOUBLE / (SELECT hi - lo - {P.w - 2} FROM bounds) AS l)""",
        "crowd",
        P,
    ),
    "state_size": sql(
        "SELECT (SELECT count(*) FROM shape) AS clusters, (SELECT count(*) FROM link) AS links, (SELECT count(*) FROM crowd) AS crowds, (SELECT count(*) FROM grp) AS groups",
        "grp",
        P,
    ),
}
_DEPTHS = {
    "ins": "SELECT group_id AS g, 1::BIGINT AS n FROM grp UNION SELECT e.dst_group, i.n + 1 FROM ins i JOIN evo e ON e.src_group = i.g",
    "outs": "SELECT group_id AS g, 1::BIGINT AS n FROM grp UNION SELECT e.src_group, o.n + 1 FROM outs o JOIN evo e ON e.dst_group = o.g",
    "deep": """SELECT group_id, win, (SELECT max(n) FROM ins i WHERE i.g = group_id) AS depth_in, (SELECT max(n) FROM outs o WHERE o.g = group_id) AS depth_out FROM grp""",
}
_CLOSED = sql(
    f"""SELECT group_id, win - depth_in + 1 AS first_win, win AS last_win, depth_in AS n_windows FROM deep
    WHERE depth_out = 1 AND depth_in >= {P.k_g} AND win < {{last}}""",
    "evo",
    P,
    _DEPTHS,
)
ORACLE_SQL |= {
    "closed_evolving_groups": _CLOSED.format(last="(SELECT max(win) FROM grp)"),
    # the stream knows the last window even where it holds no group
    "stream_closed_evolving_groups": _CLOSED.format(last=f"(SELECT max(t) - {P.w - 1} FROM shape)"),
    "case_graph_nodes": sql(
        f"""SELECT group_id, win, size, depth_in + depth_out - 1 AS life, array_to_string(members, '-') AS members
        FROM grp JOIN deep USING (group_id, win) WHERE win BETWEEN {CASE[0]} AND {CASE[1]}""",
        "evo",
        P,
        _DEPTHS,
    ),
    "evolving_families": sql(
        f"""SELECT min(m.group_id) AS family, count(*) AS n_groups, min(win) AS first_win, max(win) AS last_win, max(n) AS n_windows,
          max(n) + {P.w - 1} AS n_timestamps, max(win) < (SELECT max(win) FROM grp) AS closed
        FROM long m JOIN (SELECT g, min(other) AS low FROM tied GROUP BY g) ON g = m.group_id GROUP BY low""",
        "evo",
        P,
        _DEPTHS
        | {
            "long": f"SELECT group_id, win, depth_in + depth_out - 1 AS n FROM deep WHERE depth_in + depth_out - 1 >= {P.k_g}",
            "edge": """SELECT src_group AS a, dst_group AS b FROM evo WHERE src_group IN (SELECT group_id FROM long) AND dst_group IN (SELECT group_id FROM long)
              UNION ALL SELECT dst_group, src_group FROM evo WHERE src_group IN (SELECT group_id FROM long) AND dst_group IN (SELECT group_id FROM long)""",
            "tied": "SELECT group_id AS g, group_id AS other FROM long UNION SELECT t.g, b.b FROM tied t JOIN edge b ON b.a = t.other",
        },
    ),
}
ORACLE_SQL["ablation"] = sql(
    ORACLE_SQL["ablation"],
    "link",
    P,
    {
        "pairs": f"""SELECT b.t - a.t AS dt, {_RULES["far_hull"]} OR {_RULES["near_sound"]} AS decided,
          EXISTS (SELECT 1 FROM link l WHERE l.src = a.cluster_id AND l.dst = b.cluster_id) AS is_link,
          abs(floor(a.minx / {_LIMIT}) - floor(b.minx / {_LIMIT})) <= 1 AND abs(floor(a.miny / {_LIMIT}) - floor(b.miny / {_LIMIT})) <= 1 AS boxed
          FROM shape a JOIN shape b ON b.t > a.t AND b.t - a.t < {P.w}"""
    },
)
ORACLE_SQL |= {
    name: recall_sql(PLANTED.but(d=d, k_c=k_c), _WALKS, tracks.DISTRICT)
    for name, d, k_c in (
        ("planted_recall", 8.0, 10), ("planted_recall_no_gaps", 8.0, 14),
        ("planted_recall_published_distance", 5.0, 10), ("planted_recall_no_gaps_published_distance", 5.0, 14),
    )
}
ORACLE_SQL |= {f"prune_{n}": sql(f"SELECT a.cluster_id AS src, b.cluster_id AS dst {_PAIRS} WHERE {c}", "shape", P) for n, c in _RULES.items()}
