"""Headline queries, timed: prints one JSON line.

BENCH_SF_DIR (default /root/testdata/sf0.1) and BENCH_CPUS set the input and
the cores.  Layers are stored once before the clock starts, as the paper's
collections are; approximations are built inside the queries that build them,
and stored ones are read by the filter queries.
"""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import SparkSession  # noqa: E402

from rasterruns.grid import GridSpec  # noqa: E402
from rasterruns.operators import approximate, mbr  # noqa: E402
from rasterruns.operators.refine import refine  # noqa: E402
from rasterruns.plans import join  # noqa: E402
from rasterruns.queries.spatial import layer  # noqa: E402
from rasterruns.runtime import materialize  # noqa: E402


def main() -> None:
    d = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", str(os.cpu_count()))
    conf = {"spark.master": f"local[{cpus}]", "spark.sql.shuffle.partitions": cpus, "spark.driver.memory": "8g", "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.sql.session.timeZone": "UTC", "spark.sql.files.maxPartitionBytes": "4m", "spark.sql.files.openCostInBytes": "0"}
    spark = SparkSession.builder.config(map=conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    names = ("ponds", "sites", "zones", "counties", "provinces", "tracks")
    at = {n: layer(spark, d, n).repartition(4 * int(cpus)) for n in names}
    at = {n: materialize(x) for n, x in at.items()}
    seconds: dict[str, float] = {}

    def clock(name: str, f) -> None:
        start = time.perf_counter()
        f()
        seconds[name] = round(time.perf_counter() - start, 3)

    def sink(df) -> None:
        df.write.format("noop").mode("overwrite").save()

    grid = GridSpec(14)
    stages: dict[str, dict] = {}
    sink(approximate.build_dual(at["sites"], GridSpec(8)))  # starts the workers
    for n in ("sites", "ponds", "zones", "counties"):
        clock(f"construct_onestep_{n}", lambda n=n: sink(approximate.build_dual(at[n], grid)))
        clock(f"construct_onestep_pip_{n}", lambda n=n: sink(approximate.build_dual(at[n], grid, "onestep_pip")))
    # the constructions that keep every cell, at an order that suits them
    for m in ("onestep_neighbours", "scanline", "flood", "clip", "object_grid"):
        clock(f"construct_{m}_sites_11", lambda m=m: sink(approximate.build_dual(at["sites"], GridSpec(11), m)))
    clock("construct_coded_sites", lambda: sink(approximate.build_coded(at["sites"], GridSpec(12))))
    clock("construct_dual_sites_12", lambda: sink(approximate.build_dual(at["sites"], GridSpec(12))))
    dual = {n: materialize(approximate.build_dual(at[n], grid)) for n in ("sites", "ponds", "zones", "counties")}
    dual["provinces"] = materialize(approximate.build_dual(at["provinces"], GridSpec(12)))
    hulls = {n: materialize(approximate.build_corner_hull(at[n])) for n in ("sites", "ponds")}
    rasters = {n: materialize(approximate.build_local_raster(at[n], 150)) for n in ("ponds", "counties")}

    def staged(name: str, pairs, r: str, s: str, method: str, approx, predicate: str = "intersects") -> None:
        """A join after the box stage; its filter and exact test are also kept apart, with what the filter leaves."""
        found = []
        clock(f"{name}/filter", lambda: found.append(materialize(join.verdicts(pairs, at[r], at[s], predicate, method, approx=approx))))
        large = join.larger_side(at[r], at[s]) if predicate == "intersects" else None
        clock(f"{name}/exact", lambda: sink(refine(found[0].where("verdict = 'unsure'"), at[r], at[s], predicate, large)))
        n = {x.verdict: x["count"] for x in found[0].groupBy("verdict").count().collect()}
        stages[name] = {"filter": seconds.pop(f"{name}/filter"), "exact": seconds.pop(f"{name}/exact"), "candidates": sum(n.values()), "unsure_pct": round(100 * n.get("unsure", 0) / max(1, sum(n.values())), 2)}
        seconds[name] = round(stages[name]["filter"] + stages[name]["exact"], 3)

    for r, s in (("sites", "ponds"), ("ponds", "zones"), ("ponds", "counties"), ("ponds", "provinces")):
        pairs = materialize(mbr.mbr_join(at[r], at[s]).drop("tile_id"))
        a = dual[r] if s != "provinces" else materialize(approximate.build_dual(at[r], GridSpec(12)))
        clock(f"mbr_join_{r}_{s}", lambda r=r, s=s: sink(mbr.mbr_join(at[r], at[s])))
        clock(f"direct_{r}_{s}", lambda r=r, s=s, p=pairs: sink(refine(p, at[r], at[s], large=join.larger_side(at[r], at[s]))))
        staged(f"dual_{r}_{s}", pairs, r, s, "dual", (a, dual[s]))
        packed = [materialize(approximate.compress(x)) for x in (a, dual[s])]
        staged(f"dual_compressed_{r}_{s}", pairs, r, s, "dual_compressed", packed)
        if r == "sites":
            staged(f"corner_hull_{r}_{s}", pairs, r, s, "corner_hull", (hulls[r], hulls[s]))
        if s == "counties":
            staged(f"local_raster_{r}_{s}", pairs, r, s, "local_raster", (rasters[r], rasters[s]))
    coded = [materialize(approximate.build_coded(at[n], GridSpec(12), side)) for n, side in (("sites", "R"), ("counties", "S"))]
    plain = [materialize(approximate.build_dual(at[n], GridSpec(12))) for n in ("sites", "counties")]
    pairs = materialize(mbr.mbr_join(at["sites"], at["counties"]).drop("tile_id"))
    clock("filter_coded_sites_counties", lambda: sink(join.verdicts(pairs, at["sites"], at["counties"], method="coded", approx=tuple(coded))))
    clock("filter_dual_sites_counties", lambda: sink(join.verdicts(pairs, at["sites"], at["counties"], approx=tuple(plain))))
    clock("within_ponds_counties", lambda: sink(join.spatial_join(at["ponds"], at["counties"], "within", grid=grid).pairs))
    clock("lines_counties_tracks", lambda: sink(join.spatial_join(at["counties"], at["tracks"], "line", grid=GridSpec(12)).pairs))
    print(json.dumps({"metric": "headline_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "stages": stages, "sf": d.rstrip("/").rsplit("sf", 1)[-1]}))
    spark.stop()


if __name__ == "__main__":
    main()
