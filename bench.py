"""Times the headline queries; prints one JSON line.

Environment: BENCH_SF_DIR (default /root/testdata/sf0.1), BENCH_CPUS (default 8).
"""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import SparkSession  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.driver.memory", "16g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from groupflow.operators import baselines, chains, density, lineage, links, peel
    from groupflow.params import Params
    from groupflow.plans import experiments
    from groupflow.plans.pipeline import clusters, discover
    from groupflow.sources import tracks
    from groupflow.storage import materialize

    times: dict[str, float] = {}
    info: dict[str, float] = {}

    def timed(name, run):
        began = time.time()
        out = run()
        times[name] = round(time.time() - began, 3)
        return out

    spark.range(1).count()
    # ten times the objects of sf0.01 on the same ground: a third of the distances
    dense = SF.rstrip("/").endswith("sf0.1")
    p = Params(eps=2.0, min_pts=6, w=8, k_c=6, m_c=6, k_p=3, m_p=3, d=4.0, m_g=0.7, k_g=4) if dense else Params()
    snap = timed("interpolate", lambda: materialize(tracks.hourly_events(spark, SF), "snap"))
    member, shape = timed("clusters", lambda: clusters(snap, p))
    link = timed("links_box", lambda: materialize(links.build(shape, p), "link"))
    timed("links_grid", lambda: links.build(shape, p, "grid").count())
    timed("links_sector", lambda: links.build(shape, p, "sector", n_parts=int(CPUS)).count())
    timed("links_random", lambda: links.build(shape, p, "random", n_parts=int(CPUS)).count())
    timed("links_none", lambda: links.build(shape, p, "none", False).count())
    cover = timed("cover", lambda: materialize(chains.cover(link), "cover"))
    crowd = timed("closed_crowds", lambda: chains.closed_crowds(shape, cover, p))
    agg = timed("peel", lambda: materialize(peel.peel(crowd, shape, p), "agg"))
    windows = timed("closure", lambda: materialize(peel.closed(peel.by_window(agg)), "windows"))
    group = timed("groups", lambda: materialize(peel.groups(windows), "group"))
    evo = timed("evolution", lambda: materialize(lineage.edges(group, p.m_g), "evo"))
    # families of long-lived groups over the whole range: listed chains multiply with splits and merges, families do not
    family = timed("evolving_groups", lambda: materialize(lineage.families(group, evo, p.k_g, p.w), "family"))
    # beside the phases: the other cluster plan, the competitors, and growing numbers of objects
    if os.environ.get("BENCH_EXPERIMENTS", "1") != "0":
        timed("strict_crowds", lambda: baselines.strict_crowds(shape, link, p.k_c).count())
        timed("cut_at_invalid", lambda: baselines.cut_at_invalid(crowd, shape, p.k_c, p.k_p, p.m_p).count())
        timed("clusters_grid", lambda: density.cluster(snap, p.eps, p.min_pts, plan="grid").count())
        for part, some, q in experiments.objects(snap, p, 2)[:1]:
            timed(f"all_phases_{part:g}_of_objects", lambda some=some, q=q: discover(some, q).evo.count())
    n = snap.agg((F.max("t") - F.min("t") + 2 - p.w).alias("n")).first()["n"]
    steps = ("clusters", "links_box", "cover", "closed_crowds", "peel", "closure", "groups", "evolution", "evolving_groups")
    whole = sum(times[s] for s in steps)
    info |= {"windows": n, "ms_per_window": round(1000 * whole / n, 1), "clusters": shape.count(), "links": link.count(), "crowds": crowd.count(), "groups": group.count(), "evolution_edges": evo.count(), "evolving_groups": family.count()}
    print(
        json.dumps({"metric": "moving groups, all phases", "value": round(whole, 3), "unit": "sec", "queries": times, "sf": SF.rsplit("sf", 1)[-1], **info})
    )


if __name__ == "__main__":
    main()
