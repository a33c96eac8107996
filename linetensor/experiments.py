"""The published experiments, re-expressed on the workload tensors.

``python -m linetensor.experiments e06 --dir /root/testdata/sf0.1 --cores 8`` prints one JSON line a
row. Timings are our own runs on this machine, after a warm-up, into the noop sink; they are ratios
between our implementations and say nothing about other hardware.
"""

from __future__ import annotations

import argparse
import json
import math
import time
from collections.abc import Callable, Iterator

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from . import measures
from .functions.bitplan import BitPlan
from .operators import baselines
from .operators.factors import RANK
from .operators.kernels import kr, kr_all_modes
from .operators.packed import PackedTensor, TensorShape, flag_boundary, pack, segment, sort_line
from .plans.choose import choose_resolution, tensor_class
from .plans.cpals import cp_als, packed_kernel
from .queries import QUERIES, factors_for
from .sources.tensors import checkpointed
from .sources.workloads import WORKLOADS

SEGMENTS = 8
TIMED = ("w01", "w02", "w04", "w05", "w07", "w08")
EXPERIMENTS: dict[str, Callable[[SparkSession, str], Iterator[dict]]] = {}


def experiment(function: Callable[[SparkSession, str], Iterator[dict]]) -> Callable:
    EXPERIMENTS[function.__name__] = function
    return function


def _stored(spark: SparkSession, d: str, name: str) -> tuple[DataFrame, PackedTensor, list[DataFrame]]:
    """A workload's coordinate list and cut packed tensor, both written so that timings start from storage."""
    w = WORKLOADS[name]
    coo = checkpointed(w.build(spark, d))
    t = segment(pack(coo, names=w.modes), SEGMENTS)
    t = t.with_df(checkpointed(t.df), boxes=checkpointed(t.boxes))
    return coo, t, factors_for(t, w)


def _mean(run: Callable[[], DataFrame], runs: int = 2) -> float:
    return float(np.mean(measures.timed(run, 1, runs)))


def _formats(coo: DataFrame, t: PackedTensor, factors: list[DataFrame]) -> dict[tuple[str, str], Callable[[int], DataFrame]]:
    """By (family, variant) the kernel of a mode. Trees are built once for each root, as copies."""
    lengths = t.shape.lengths
    blocks = {bits: baselines.blk_build(coo, lengths, super_bits=bits) for bits in (10, 14)}
    trees = {tile: baselines.csf_build_all(coo, lengths, tile) for tile in (None, 64)}
    return {
        ("general", "coo"): lambda m: baselines.coo_kr(coo, factors, m, lengths),
        ("general", "coo_private"): lambda m: baselines.coo_kr(coo, factors, m, lengths, private=True),
        ("general", "blk10"): lambda m: baselines.blk_kr(blocks[10], factors, m),
        ("general", "blk14"): lambda m: baselines.blk_kr(blocks[14], factors, m),
        ("specific", "csf"): lambda m: baselines.csf_kr(trees[None][m], factors, m),
        ("specific", "csf_tile"): lambda m: baselines.csf_kr(trees[64][m], factors, m),
        ("ours", "packed"): lambda m: kr(t, factors, m),
    }


@experiment
def e01(spark: SparkSession, d: str) -> Iterator[dict]:
    """Elements of spatial blocks."""
    for name, w in WORKLOADS.items():
        yield {"workload": name, **measures.block_stats(w.build(spark, d)).first().asDict()}


@experiment
def e02(spark: SparkSession, d: str) -> Iterator[dict]:
    """The worked example."""
    plan = BitPlan.adaptive((4, 8, 2))
    yield {"masks": plan.masks(), "groups": plan.groups(), "subspaces": [plan.subspace(q) for q in range(4)], "line": plan.line_length(), "morton": BitPlan.morton((4, 8, 2)).line_length()}


@experiment
def e03(spark: SparkSession, d: str) -> Iterator[dict]:
    """Our index against the fractal curve."""
    for name, w in WORKLOADS.items():
        lengths = pack(w.build(spark, d)).shape.lengths
        yield {"workload": name, "bits": measures.mask_bits(lengths), "morton_bits": measures.morton_bits(lengths), "factor": measures.line_factor(lengths)}


@experiment
def e04(spark: SparkSession, d: str) -> Iterator[dict]:
    """The table of tensors."""
    for name, w in WORKLOADS.items():
        t = pack(w.build(spark, d), names=w.modes)
        yield {"workload": name, "lengths": t.shape.lengths, "nnz": t.count(), "density": measures.density(t.shape.lengths, t.count()), "class": tensor_class(t.count(), t.shape.lengths)}


@experiment
def e05(spark: SparkSession, d: str) -> Iterator[dict]:
    """All-modes speedup over the best general and the best specific format of each tensor, with geometric means."""
    rows = list(e06(spark, d))
    table = spark.createDataFrame([(r["workload"], r["family"], r["variant"], r["seconds"]) for r in rows], "workload string, family string, variant string, seconds double")
    best = {(r["workload"], r["family"]): r["best"] for r in measures.oracle_best(table).collect()}
    for family in ("general", "specific"):
        gains = {n: best[n, family] / best[n, "ours"] for n in TIMED if (n, family) in best and (n, "ours") in best}
        yield {"family": family, "geomean_speedup": math.exp(np.mean(np.log(list(gains.values())))), "by_workload": gains}
    for r in QUERIES["compression_summary"](spark, d).where("workload = 'geomean'").collect():
        yield {"family": r["family"], "geomean_compression": r["compression"]}


@experiment
def e06(spark: SparkSession, d: str) -> Iterator[dict]:
    """All-modes seconds by format."""
    for name in TIMED:
        coo, t, factors = _stored(spark, d, name)
        for (family, variant), run in _formats(coo, t, factors).items():
            seconds, status = measures.attempt(lambda run=run, t=t: sum(_mean(lambda m=m: run(m)) for m in range(t.shape.order)))
            yield {"workload": name, "family": family, "variant": variant, "seconds": seconds, "status": status}


@experiment
def e07(spark: SparkSession, d: str) -> Iterator[dict]:
    """Seconds by mode and their variation."""
    for name in ("w01", "w02", "w03", "w07"):
        coo, t, factors = _stored(spark, d, name)
        for (_, variant), run in _formats(coo, t, factors).items():
            timed = [measures.attempt(lambda run=run, m=m: _mean(lambda: run(m))) for m in range(t.shape.order)]
            seconds, status = [s for s, _ in timed], next((s for _, s in timed if s != "ok"), "ok")
            yield {"workload": name, "variant": variant, "seconds": seconds, "status": status, "variation": measures.mode_variation(seconds) if status == "ok" else None}


@experiment
def e08(spark: SparkSession, d: str) -> Iterator[dict]:
    """Roofline points: operations a second reached and attainable, with this machine's own triad and dense product; bytes are the model's."""
    bandwidth, peak = measures.stream_bandwidth(), measures.peak_flops()
    for name, mode in (("w05", 3), ("w01", 2), ("w08", 0), ("w02", 1), ("w02", 0)):
        _, t, factors = _stored(spark, d, name)
        flops, moved = measures.kernel_work(t.count(), t.shape.order, RANK, t.plan.limbs, t.shape.lengths[mode])
        seconds = _mean(lambda t=t, factors=factors, mode=mode: kr(t, factors, mode))
        yield {"workload": name, "mode": mode + 1, "intensity": flops / moved, "reached": flops / seconds, "bound": measures.roofline(peak, bandwidth, flops, moved)}


@experiment
def e09(spark: SparkSession, d: str) -> Iterator[dict]:
    """Rank as columns against the generic forms."""
    for name in ("w01", "w04", "w05"):
        _, t, factors = _stored(spark, d, name)
        seconds = {impl: _mean(lambda impl=impl, t=t, factors=factors: kr(t, factors, 0, rank_impl=impl)) for impl in ("columns", "array", "long", "arrow")}
        yield {"workload": name, "seconds": seconds, "gain_over_array": seconds["array"] / seconds["columns"]}


@experiment
def e10(spark: SparkSession, d: str) -> Iterator[dict]:
    """Storage of every format."""
    for name in WORKLOADS:
        yield {"workload": name, **{r["format"]: r["bytes"] for r in QUERIES[f"storage_{name}"](spark, d).collect()}}


@experiment
def e11(spark: SparkSession, d: str) -> Iterator[dict]:
    """Construction seconds from a coordinate list; trees start from one that is sorted already."""
    for name in TIMED:
        w = WORKLOADS[name]
        coo = checkpointed(w.build(spark, d))
        shape = pack(coo, names=w.modes).shape
        lengths = shape.lengths
        presorted = checkpointed(coo.orderBy(*[f"c{m + 1}" for m in baselines.tree_levels(lengths, 0)]))
        builds = {
            "packed": lambda coo=coo, shape=shape: sort_line(pack(coo, shape)).df,
            "blk10": lambda coo=coo, lengths=lengths: baselines.blk_build(coo, lengths).elements,
            "csf": lambda p=presorted, lengths=lengths: baselines.csf_build(p, lengths, 0).df,
        }
        seconds = {k: _mean(f) for k, f in builds.items()}
        packed = pack(coo, shape)
        held = packed.with_df(checkpointed(packed.df))
        cut = segment(held, SEGMENTS)
        cut = cut.with_df(checkpointed(cut.df), boxes=checkpointed(cut.boxes))
        steps = {"encode": lambda p=packed: p.df, "sort": lambda h=held: sort_line(h).df, "segment": lambda h=held: segment(h, SEGMENTS).df, "flag": lambda c=cut: flag_boundary(c, 1).df}
        seconds |= {k: _mean(f) for k, f in steps.items()}
        yield {"workload": name, "seconds": seconds, "comparisons": {"packed": measures.comparison_model(coo.count(), BitPlan.adaptive(lengths).limbs), "coo": measures.comparison_model(coo.count(), len(lengths))}}


@experiment
def e12(spark: SparkSession, d: str) -> Iterator[dict]:
    """The same decomposition through any format: fits, sweeps and the greatest difference of factors."""
    for name in ("w12", "w05"):
        coo, t, _ = _stored(spark, d, name)
        lengths = t.shape.lengths
        kernels = {"packed": packed_kernel(t), "coo": lambda f, m, coo=coo, n=lengths: baselines.coo_kr(coo, f, m, n), "csf": lambda f, m, coo=coo, n=lengths: baselines.csf_kr(baselines.csf_build(coo, n, m), f, m)}
        models = {k: cp_als(t.df, kernel, lengths, 4, 3) for k, kernel in kernels.items()}
        for k, model in models.items():
            worst = max(measures.compare_factors(a, b) for a, b in zip(model.factors, models["packed"].factors, strict=True))
            yield {"workload": name, "format": k, "sweeps": model.iterations, "fit": model.fits[-1], "difference": worst}


@experiment
def e13(spark: SparkSession, d: str) -> Iterator[dict]:
    """Speedup over the sequential kernel on this session's cores; run the module with several --cores for a scaling curve."""
    cores = spark.sparkContext.defaultParallelism
    for name in ("w01", "w02", "w05"):
        _, t, factors = _stored(spark, d, name)
        alone = _mean(lambda t=t, factors=factors: kr(t, factors, 0, "sequential"))
        seconds = _mean(lambda t=t, factors=factors: kr(t, factors, 0))
        gain = measures.speedup(alone, seconds)
        yield {"workload": name, "cores": cores, "sequential": alone, "parallel": seconds, "speedup": gain, "efficiency": measures.efficiency(gain, cores)}


@experiment
def e14(spark: SparkSession, d: str) -> Iterator[dict]:
    """Every resolution forced, beside the adaptive choice."""
    for name in ("w01", "w02", "w03", "w04", "w06", "w07"):
        _, t, factors = _stored(spark, d, name)
        seconds = {r: _mean(lambda r=r, t=t, factors=factors: kr(t, factors, 0, r)) for r in ("buffered", "direct", "flagged")}
        conflicts = measures.conflict_stats(t, 0).first().asDict()
        yield {"workload": name, "seconds": seconds, "chosen": choose_resolution(t.count(), t.shape.lengths[0]), **conflicts}


@experiment
def e15(spark: SparkSession, d: str) -> Iterator[dict]:
    """One limb against two: the same tensor with a mode declared so long that positions need two."""
    coo, t, factors = _stored(spark, d, "w01")
    wide = TensorShape(t.shape.names, (*t.shape.lengths[:2], 1 << 60))
    two = pack(coo, wide)
    two = two.with_df(checkpointed(sort_line(two).df))
    narrow, broad = (_mean(lambda x=x: kr(x.with_df(x.df, nnz=t.count()), factors, 0, "direct", delivery="broadcast")) for x in (t, two))
    yield {"one_limb": narrow, "two_limbs": broad, "limbs": two.plan.limbs, "ratio": broad / narrow}


def all_modes_seconds(t: PackedTensor, factors: list[DataFrame]) -> float:
    """One pass over all modes, started together."""
    start = time.perf_counter()
    for out in kr_all_modes(t, factors):
        out.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start


def main() -> None:
    parser = argparse.ArgumentParser(description=__doc__)
    parser.add_argument("names", nargs="*", default=sorted(EXPERIMENTS))
    parser.add_argument("--dir", default="/root/testdata/sf0.01")
    parser.add_argument("--cores", default="8")
    args = parser.parse_args()
    spark = SparkSession.builder.master(f"local[{args.cores}]").config("spark.sql.shuffle.partitions", args.cores).config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.warehouse.dir", "/tmp/linetensor-experiments").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for name in args.names:
        for row in EXPERIMENTS[name](spark, args.dir):
            print(json.dumps({"experiment": name, "dir": args.dir, "cores": args.cores, **row}, default=str), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
