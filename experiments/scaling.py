"""Strong scaling: the same searches with more and more local cores, plain and reordered.

python -m experiments.scaling SCALE THREADS   prints one line of JSON; run it once for each count of threads.
"""

from __future__ import annotations

import json
import sys
import time

from experiments.session import local


def main(scale: int, threads: int) -> None:
    spark = local(threads)
    from pyspark.sql import functions as F

    from levelgraph.bfs import hybrid
    from levelgraph.graph import build
    from levelgraph.graph.kronecker import kronecker
    from levelgraph.reorder import level_order as lo
    from levelgraph.runtime import materialize

    plain = kronecker(spark, scale, shuffle_labels=True)
    edges = plain.raw_edges.count()
    plain.ranked_arcs.count()
    began = time.perf_counter()
    perm = materialize(lo.reverse_level_order(plain, isolated="drop"), "perm")
    reorder = time.perf_counter() - began
    tidy = build.Graph(build.relabel(plain.edges, perm).select(F.col("u").alias("src"), F.col("v").alias("dst")), perm.select(F.col("label").alias("v")), "tidy")
    hybrid.prepare(tidy)
    hybrid.lists_in_order(plain, "id").count()
    source = hybrid.sample_sources(plain, 1).first()["v"]
    label = perm.where(F.col("v") == source).first()["label"]
    out = {"scale": scale, "threads": threads, "reorder_seconds": round(reorder, 3)}
    for name, graph, start, options in (("plain", plain, source, hybrid.VARIANTS["base"]), ("reordered", tidy, label, hybrid.VARIANTS["reordered_lb_vec"])):
        seconds = [hybrid.bfs(graph, start, **options).seconds for _ in range(3)]
        out[f"{name}_seconds"] = round(min(seconds), 3)
        out[f"{name}_teps"] = round(edges / min(seconds), 1)
    print(json.dumps(out))
    spark.stop()


if __name__ == "__main__":
    main(int(sys.argv[1]), int(sys.argv[2]))
