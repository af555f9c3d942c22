"""From vectors to a snapshot: encode, partition, rebalance, quantise, pad."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import Config
from ..operators import coarse, codebook, encode, shaping
from ..operators.search import Snapshot
from ..session import written


def build_snapshot(vectors: DataFrame, cfg: Config, v_max: float | None = None, init: str = "hash", iters: int = 5, seed: int = 0, mode: str = "window", balance: bool = True, payload: DataFrame | None = None, train_rows: int | None = None) -> Snapshot:
    """vectors: (vec_id, embedding). cfg.pipeline 'zk' works on fixed-point integers, 'std' on doubles.

    balance=False pads to the largest list instead (cfg.slots is then replaced); train_rows bounds the rows that
    k-means sees, chosen by a hash of their ids. Every vector is assigned and encoded.
    """
    exact = cfg.pipeline == "zk"
    bound = encode.coordinate_bound(vectors) if v_max is None else v_max
    real = F.transform("embedding", lambda x: x.cast("double"))
    vec = written(vectors.select("vec_id", (encode.fixed(F.col("embedding"), bound, cfg.scale_bits) if exact else real).alias("v")), "vectors")
    n0 = vec.count()
    if balance:
        cfg.validate(n0)
    few = lambda d: d if train_rows is None or n0 <= train_rows else written(d.orderBy(F.xxhash64("vec_id"), "vec_id").limit(train_rows), "training")
    sample = few(vec)
    cent = coarse.train_coarse(sample, cfg.n_list, iters, seed, init, exact=exact)
    cent = written(cent, "centroids")
    assign = written(coarse.assign_coarse(vec, cent, exact=exact), "assign")
    moves = None
    if balance:
        assign, moves = shaping.rebalance(vec, assign, cent, cfg.n_list, cfg.slots, mode, n0=n0)
    else:
        cfg = replace(cfg, slots=max(1, shaping.naive_capacity(assign)))
    resid = written(coarse.residuals(vec, assign, cent), "residuals")
    words = written(codebook.train_codebooks(few(resid), cfg.blocks, cfg.codes, cfg.width, iters, exact, "stride" if init == "stride" else "hash", seed), "codebooks")
    codes = codebook.encode_codes(resid, words)
    slots = written(shaping.pad_slots(codes, cfg.n_list, cfg.slots, cfg.blocks, payload).repartition("list_id").sortWithinPartitions("list_id", "slot"), "slots")
    return Snapshot(cfg, bound, cent, words, slots, assign, moves, {"vec": vec, "resid": resid})


def encode_queries(queries: DataFrame, snap: Snapshot) -> DataFrame:
    """(query_id, q). A coordinate beyond the public bound is an error, not a clip."""
    q = encode.fixed(F.col("embedding"), snap.v_max, snap.cfg.scale_bits) if snap.exact else F.transform("embedding", lambda x: x.cast("double"))
    out = queries.select("query_id", q.alias("q"))
    if snap.exact:
        far = F.exists("q", lambda x: F.abs(x) > snap.cfg.scale)
        out = out.withColumn("q", F.when(far, F.raise_error(F.lit("a query leaves the public coordinate bound"))).otherwise(F.col("q")))
    return out
