"""Headline queries, timed: one line of JSON.

BENCH_SF_DIR names the tables, BENCH_CPUS the threads. Besides whole queries it times the
chain of 512 filters on a 1024 x 1024 image by pixel type, method and number of processes, by
chain length and by shape, and the size up to which a chain beats one large filter.
"""

from __future__ import annotations

import json
import os
import sys
import time

import numpy as np

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

HEADLINES = ("erode_s3_emb", "chain_erode_64_emb", "chain512_u8", "chain_fused_64_emb", "chain_rounds_64_emb", "hmax_emb", "dome_emb", "hfill_order", "raobj_emb", "open_rec75_strip", "qdt_emb", "pattern_spectrum_part", "asf11_order", "raster_ship", "doc_open", "pattern_spectrum_docs", "stream_chain_emb")


TYPES = (("u8", np.uint8), ("u16", np.uint16), ("f32", np.float32), ("f64", np.float64))


def best(chain, a: np.ndarray, n: int, together: int = 16, reps: int = 3) -> float:
    return round(min(chain.run(a, n, together=together)[1] for _ in range(reps)), 1)


def kernels(cpus: int) -> dict:
    """Milliseconds of 512 filters on one image of 1024 x 1024 by type: strips in shared memory by number of
    processes, one filter a turn (whole image, a barrier after each), one whole-array pass a filter in one process,
    and the fused filter. The queue is interpreted Python: its figure is one filter of an eighth by an eighth of
    the image, multiplied, and says nothing of compiled code."""
    from rasterchain import kernels as K
    from rasterchain import measures as m
    from rasterchain.exec.shared import SharedChain

    rng, out = np.random.default_rng(1), {}
    for name, kind in TYPES:
        a = rng.integers(0, 255, (1024, 1024)).astype(kind)
        row = {"one_process_ms": round(m.timed(lambda a=a: K.chain3(a, 512), 1), 1), "whole_array_ms": round(m.timed(lambda a=a: K.chain3(a, 512, block_rows=1024, together=1), 1), 1), "fused_ms": round(m.timed(lambda a=a: K.prefix_suffix(a, 512), 3), 1)}
        for workers in sorted({1, 2, 4, cpus}):
            with SharedChain(a.shape, kind, workers) as chain:
                row[f"processes_{workers}_ms"] = best(chain, a, 512)
                row[f"barrier_{workers}_ms"] = best(chain, a, 512, 1, 1)
                if workers == cpus:
                    row["by_length_ms"] = {n: best(chain, a, n) for n in (1, 4, 16, 64, 128, 512)}
        one = row[f"processes_{cpus}_ms"]
        row |= {"scaling": round(m.scaling(row["processes_1_ms"], one), 1), "throughput_mpx_s": round(m.throughput(512, cpus, 1024, 1024, one), 1), "over_barrier": round(row[f"barrier_{cpus}_ms"] / one, 2), "over_whole_array": round(row["whole_array_ms"] / one, 1)}
        row["queue_ms_extrapolated"] = round(512 * 64 * m.timed(lambda a=a[:128, :128]: K.queue(a, 1), 1), 1)
        out[name] = row
    return out


def shapes(cpus: int) -> dict:
    """Milliseconds of 512 filters on bytes by shape: squares, and one side of 128 with the other growing."""
    from rasterchain.exec.shared import SharedChain

    rng, out = np.random.default_rng(2), {}
    for kind, sizes in (("square", [(n, n) for n in (128, 256, 512, 1024, 2048)]), ("width", [(128, n) for n in (128, 512, 2048, 8192)]), ("height", [(n, 128) for n in (128, 512, 2048, 8192)])):
        for shape in sizes:
            with SharedChain(shape, np.uint8, cpus) as chain:
                out[f"{kind}_{max(shape)}"] = best(chain, rng.integers(0, 255, shape).astype(np.uint8), 512)
    return out


def break_even() -> dict:
    """Largest size of the grid at which a chain of elementary filters is at least as fast as one filter of that size by running extrema."""
    from rasterchain import kernels as K
    from rasterchain import measures as m

    rng, out = np.random.default_rng(3), {}
    for name, kind in TYPES:
        a = rng.integers(0, 255, (512, 512)).astype(kind)
        wins = [s for s in (1, 2, 3, 5, 8, 13, 20, 40, 60, 80, 91, 100) if m.timed(lambda a=a, s=s: K.chain3(a, s), 3) <= m.timed(lambda a=a, s=s: K.prefix_suffix(a, s), 3)]
        out[name] = max(wins, default=0)
    return out


def main() -> None:
    from pyspark.sql import SparkSession

    from rasterchain import workloads

    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = int(os.environ.get("BENCH_CPUS", os.cpu_count() or 4))
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", str(cpus)).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "6g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("OFF")
    workloads.QUERIES["erode_s1_emb"](spark, sf).write.format("noop").mode("overwrite").save()  # warms the workers
    took = {}
    for name in HEADLINES:
        t = time.perf_counter()
        workloads.QUERIES[name](spark, sf).write.format("noop").mode("overwrite").save()
        took[name] = round(time.perf_counter() - t, 3)
    spark.stop()
    print(json.dumps({"metric": "total seconds of headline queries", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": sf, "kernels": kernels(cpus), "shapes_ms": shapes(cpus), "break_even_size": break_even()}))


if __name__ == "__main__":
    main()
