"""Training by rounds: broadcast parameters, gradients at the sites, one averaged step."""

from __future__ import annotations

import math
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .features import Normalizer, matrix_of
from .loss import loss_gradient
from .network import EncoderSpec, backward, forward, init_params
from .sampling import diverse_batch, uniform_batch


@dataclass(frozen=True)
class TrainConfig:
    n_rounds: int = 20
    batch: int = 32
    lr: float = 0.02
    lam: float = 5.0
    t: float = 5.0
    pairing: str = "all"
    selector: str = "diverse"  # or uniform
    weighting: str = "batch"  # or equal
    merge: str = "gradient"  # or parameter
    local_steps: int = 1
    grad_dtype: str = "float32"
    tol: float = 0.0
    seed: int = 0


@dataclass
class Trained:
    spec: EncoderSpec
    params: np.ndarray
    history: list[dict] = field(default_factory=list)
    snapshots: dict[int, np.ndarray] = field(default_factory=dict)


def site_step(spec: EncoderSpec, params: np.ndarray, x: np.ndarray, cfg: TrainConfig, seed: int) -> tuple[np.ndarray, float, int]:
    """(gradient, or moved parameters, of one site; loss; samples used)."""
    own, loss, used = params, 0.0, 0
    steps = cfg.local_steps if cfg.merge == "parameter" else 1
    for s in range(steps):
        if cfg.selector == "diverse":
            at = diverse_batch(forward(spec, own, x, "sign"), cfg.batch, seed + s)
        else:
            at = uniform_batch(len(x), cfg.batch, seed + s)
        part = x[at]
        grad, (value, _) = backward(spec, own, part, lambda h, part=part: loss_gradient(part, h, cfg.lam, cfg.t, cfg.pairing, seed))
        loss, used = loss + value / steps, len(at)
        if cfg.merge == "parameter":
            own = own - cfg.lr * grad
    return (own if cfg.merge == "parameter" else grad), loss, used


def _site_batches(shared, spec: EncoderSpec, cfg: TrainConfig, normalizer: Normalizer, round_: int):
    def run(batches):
        params = shared.value
        for batch in batches:
            for i in range(batch.num_rows):
                site = batch.column(0)[i].as_py()
                x = normalizer.apply(matrix_of(batch.column(1)[i].values))
                vector, loss, used = site_step(spec, params, x, cfg, cfg.seed * 1_000_003 + round_ * 1009 + site)
                data = vector.astype(cfg.grad_dtype).astype("<f4").tobytes()
                yield pa.RecordBatch.from_arrays([pa.array([site], pa.int32()), pa.array([used], pa.int32()), pa.array([loss]), pa.array([data], pa.binary())], names=["site_id", "used", "loss", "data"])

    return run


def _add(weighting: str):
    def run(key, frame):
        import pandas as pd

        w = frame["used"].to_numpy(float) if weighting == "batch" else np.ones(len(frame))
        frame = frame.assign(w=w).sort_values("site_id")
        total = sum(np.frombuffer(d, "<f4").astype(float) * x for d, x in zip(frame["data"], frame["w"]))
        return pd.DataFrame({"group": [int(key[0])], "w": [frame["w"].sum()], "loss": [(frame["loss"] * frame["w"]).sum()], "data": [np.asarray(total).tobytes()]})

    return run


def train_round(pool: DataFrame, spec: EncoderSpec, params: np.ndarray, cfg: TrainConfig, normalizer: Normalizer, round_: int, n_sites: int) -> tuple[np.ndarray, float]:
    """One round over pool(site_id, n, vecs): (next parameters, loss). No shuffle, unless the sites' vectors are large together."""
    spark = pool.sparkSession
    shared = spark.sparkContext.broadcast(params)
    up = pool.select("site_id", "vecs").mapInArrow(_site_batches(shared, spec, cfg, normalizer, round_), "site_id int, used int, loss double, data binary")
    if n_sites * spec.n_params * 4 > 64 << 20:  # two levels: groups of about the root of the sites
        group = F.pmod("site_id", F.lit(max(1, math.isqrt(n_sites))))
        rows = up.groupBy(group.alias("group")).applyInPandas(_add(cfg.weighting), "group int, w double, loss double, data binary").orderBy("group").collect()
        weights = np.array([r["w"] for r in rows])
        total = sum(np.frombuffer(r["data"]) for r in rows) / weights.sum()
        loss = sum(r["loss"] for r in rows) / weights.sum()
    else:
        rows = sorted(up.collect(), key=lambda r: r["site_id"])
        weights = np.array([float(r["used"]) if cfg.weighting == "batch" else 1.0 for r in rows])
        total = sum(np.frombuffer(r["data"], "<f4").astype(float) * w for r, w in zip(rows, weights)) / weights.sum()
        loss = sum(r["loss"] * w for r, w in zip(rows, weights)) / weights.sum()
    shared.unpersist()
    return (total if cfg.merge == "parameter" else params - cfg.lr * total), float(loss)


def train_encoder(pool: DataFrame, spec: EncoderSpec, cfg: TrainConfig, normalizer: Normalizer = Normalizer("none"), init: np.ndarray | None = None, keep: tuple[int, ...] = (), refresh=None, refresh_every: int = 0) -> Trained:
    """n_rounds rounds, or fewer with tol; snapshots of the rounds in keep serve shorter trainings too.

    With refresh (round -> pool), the pool is drawn anew every refresh_every rounds, so that training reaches all rows in time.
    """
    params = init_params(spec, cfg.seed) if init is None else np.array(init, float)
    n_sites = pool.count()
    out = Trained(spec, params)
    if not n_sites:
        return out
    for n in range(1, cfg.n_rounds + 1):
        if refresh and refresh_every and n > 1 and (n - 1) % refresh_every == 0:
            pool = refresh(n)
        params, loss = train_round(pool, spec, params, cfg, normalizer, n, n_sites)
        out.history.append({"round": n, "loss": loss, "bits_down": n_sites * spec.n_params * 32, "bits_up": n_sites * spec.n_params * (16 if cfg.grad_dtype == "float16" else 32)})
        if n in keep:
            out.snapshots[n] = params
        if cfg.tol and n > 1 and abs(out.history[-2]["loss"] - loss) <= cfg.tol * abs(out.history[-2]["loss"]):
            break
    out.params = params
    return out


def history_frame(spark: SparkSession, history: list[dict]) -> DataFrame:
    """``round, loss, rer, bits_up, bits_down``."""
    from .metrics import relative_error_ratio

    df = spark.createDataFrame([(h["round"], h["loss"], h["bits_up"], h["bits_down"]) for h in history], "round int, loss double, bits_up long, bits_down long")
    return relative_error_ratio(df.withColumn("run", F.lit("run"))).drop("run")


def train_many(pool: DataFrame, spec: EncoderSpec, configs: list[TrainConfig], normalizer: Normalizer = Normalizer("none"), keep: tuple[int, ...] = ()) -> list[Trained]:
    """As train_encoder for each of the configs, but a round of all of them is one job.

    A pool with a column ``config`` has sites of its own for each of them.
    """
    spark, own = pool.sparkSession, "config" in pool.columns
    sizes = {r["config"]: r["n"] for r in pool.groupBy("config").agg(F.count("*").alias("n")).collect()} if own else dict.fromkeys(range(len(configs)), pool.count())
    n_sites = sum(sizes.values())
    table = pool.select("site_id", "vecs", "config") if own else pool.select("site_id", "vecs")
    out = [Trained(spec, init_params(spec, c.seed)) for c in configs]
    for n in range(1, max(c.n_rounds for c in configs) + 1 if n_sites else 1):
        live = [i for i, c in enumerate(configs) if n <= c.n_rounds and sizes.get(i)]
        shared = spark.sparkContext.broadcast({i: out[i].params for i in live})

        def run(batches, live=live, shared=shared, n=n):
            for batch in batches:
                for r in range(batch.num_rows):
                    site = batch.column(0)[r].as_py()
                    x = normalizer.apply(matrix_of(batch.column(1)[r].values))
                    mine = [i for i in live if not own or i == batch.column(2)[r].as_py()]
                    got = [site_step(spec, shared.value[i], x, configs[i], configs[i].seed * 1_000_003 + n * 1009 + site) for i in mine]
                    data = [v.astype(configs[i].grad_dtype).astype("<f4").tobytes() for i, (v, _, _) in zip(mine, got)]
                    yield pa.RecordBatch.from_arrays([pa.array([site] * len(mine), pa.int32()), pa.array(mine, pa.int32()), pa.array([g[2] for g in got], pa.int32()), pa.array([g[1] for g in got]), pa.array(data, pa.binary())], names=["site_id", "config", "used", "loss", "data"])

        rows = sorted(table.mapInArrow(run, "site_id int, config int, used int, loss double, data binary").collect(), key=lambda r: r["site_id"])
        shared.unpersist()
        for i in live:
            mine, c = [r for r in rows if r["config"] == i], configs[i]
            w = np.array([float(r["used"]) if c.weighting == "batch" else 1.0 for r in mine])
            total = sum(np.frombuffer(r["data"], "<f4").astype(float) * x for r, x in zip(mine, w)) / w.sum()
            out[i].params = total if c.merge == "parameter" else out[i].params - c.lr * total
            out[i].history.append({"round": n, "loss": float(sum(r["loss"] * x for r, x in zip(mine, w)) / w.sum()), "bits_down": sizes[i] * spec.n_params * 32, "bits_up": sizes[i] * spec.n_params * (16 if c.grad_dtype == "float16" else 32)})
            if n in keep:
                out[i].snapshots[n] = out[i].params
    return out


def grid_search(pool: DataFrame, spec: EncoderSpec, base: TrainConfig, lams, ts, rounds, scorer, normalizer: Normalizer = Normalizer("none")) -> list[dict]:
    """A row a cell (lam, t, rounds); one training of the longest length serves all lengths.

    scorer: a list of parameters -> a list of scores (all cells at once).
    """
    cells = [(lam, t) for lam in lams for t in ts]
    got = train_many(pool, spec, [replace(base, lam=lam, t=t, n_rounds=max(rounds)) for lam, t in cells], normalizer, tuple(rounds))
    out = [{"lam": lam, "t": t, "n_rounds": n, "loss": g.history[n - 1]["loss"], "params": g.snapshots[n]} for (lam, t), g in zip(cells, got) for n in rounds]
    for cell, score in zip(out, scorer([c["params"] for c in out])):
        cell["score"] = float(score)
    return out


def code_purities(df: DataFrame, spec: EncoderSpec, params: list[np.ndarray], normalizer: Normalizer = Normalizer("none")) -> list[float]:
    """Purity of the codes of each of several encoders against ``truth``: one pass over df(vec, truth) for all of them."""
    from ..functions.bits import pack_array

    shared = df.sparkSession.sparkContext.broadcast(params)
    kind = df.schema["truth"].dataType.simpleString()

    def run(batches):
        for b in batches:
            x = normalizer.apply(matrix_of(b.column(0)))
            for i, p in enumerate(shared.value if len(x) else []):
                codes = pack_array(forward(spec, p, x, "sign") > 0)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(codes), i, np.int32)), pa.array(codes, pa.int64()), b.column(1)], names=["which", "code", "truth"])

    cells = df.select("vec", "truth").mapInArrow(run, f"which int, code long, truth {kind}").groupBy("which", "code", "truth").agg(F.count("*").alias("n"))
    best = cells.groupBy("which", "code").agg(F.max("n").alias("top"), F.sum("n").alias("n")).groupBy("which").agg((F.sum("top") / F.sum("n")).alias("purity"))
    found = {r["which"]: r["purity"] for r in best.collect()}
    return [found.get(i, 0.0) for i in range(len(params))]
