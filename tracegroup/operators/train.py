"""Training of both models: on the driver from a bounded number of pairs, or with gradients from the tasks."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tracegroup.operators.encoder import CrossEncoder, EncoderConfig, TraceEncoder, dump, restore, unit, unit_back
from tracegroup.operators.losses import bce_pair, info_nce
from tracegroup.operators.nn import Adam, Arrays
from tracegroup.operators.pairs import batches
from tracegroup.sources.storage import written


@dataclass(frozen=True)
class TrainConfig:
    """most_rows bounds the pairs or triplets that a fit on the driver reads, in an order of hashes.

    task_steps above 0 trains on the tasks instead, over all pairs: that many steps an epoch, each over an equal share of the batches.
    """

    epochs: int = 3
    batch: int = 64
    rate: float = 1e-3
    tau: float = 0.1
    denominator: str = "negatives"
    mask_same_category: bool = False
    most_rows: int = 20_000
    seed: int = 5
    task_steps: int = 0


def tokenised(traces: DataFrame, tokens: DataFrame, pieces) -> DataFrame:
    """(fp, toks): each frame's token ids as bytes of int32. traces (fp, frames); tokens (piece, tokens); pieces: a frame's pieces.

    Distinct frames are tokenised once and joined back by place.
    """
    frames = traces.select(F.explode("frames").alias("frame")).distinct().withColumn("frame_id", F.xxhash64("frame"))
    spread = frames.select("frame", F.posexplode_outer(pieces(F.col("frame"))).alias("at", "piece"))
    ids = spread.join(tokens, "piece", "left").groupBy("frame").agg(F.flatten(F.transform(F.sort_array(F.collect_list(F.struct("at", F.coalesce("tokens", F.array().cast("array<int>")).alias("t")))), lambda x: x["t"])).alias("ids"))
    return traces.select("fp", F.posexplode_outer("frames").alias("pos", "frame")).join(ids, "frame", "left").groupBy("fp").agg(F.transform(F.sort_array(F.collect_list(F.when(F.col("pos").isNotNull(), F.struct("pos", F.coalesce("ids", F.array().cast("array<int>")).alias("ids"))))), lambda x: x["ids"]).alias("toks"))


def as_bytes(toks) -> list[bytes]:
    return [np.asarray(f, np.int32).tobytes() for f in toks] if toks is not None else []


def contrastive_step(model: TraceEncoder, anchors: list, positives: list, categories: list, config: TrainConfig) -> tuple[float, Arrays]:
    """Loss and gradients of one batch; every other pair's positive is a negative."""
    n = len(anchors)
    raw, cache = model.forward([*anchors, *positives])
    u = unit(raw)
    same = np.array(categories)[:, None] == np.array(categories)[None, :] if config.mask_same_category else None
    loss, ds = info_nce(u[:n] @ u[n:].T, config.tau, config.denominator, same)
    du = np.concatenate([ds @ u[n:], ds.T @ u[:n]])
    grads: Arrays = {}
    model.backward(unit_back(raw, du), cache, grads)
    return loss, grads


def triplet_step(model: CrossEncoder, anchors: list, positives: list, negatives: list) -> tuple[float, Arrays]:
    n = len(anchors)
    score, cache = model.forward([*zip(anchors, positives, strict=True), *zip(anchors, negatives, strict=True)])
    loss, dp, dn = bce_pair(score[:n], score[n:])
    grads: Arrays = {}
    model.backward(np.concatenate([dp, dn]), cache, grads)
    return loss, grads


def _bounded(rows: DataFrame, columns: list[str], config: TrainConfig) -> list:
    return rows.select(*columns).orderBy(F.md5(F.concat_ws("|", F.lit(str(config.seed)), *columns).cast("binary")), *columns).limit(config.most_rows).collect()


def _traces_for(rows: DataFrame, columns: list[str], toks: DataFrame, config: TrainConfig) -> tuple[list, dict[str, list[bytes]]]:
    """The chosen rows, and the tokens of the traces they name and no others."""
    picked = _bounded(rows, columns, config)
    names = sorted({r[c] for r in picked for c in columns if c.endswith("_fp")})
    spark = rows.sparkSession
    wanted = spark.createDataFrame([(x,) for x in names], "fp string")
    return picked, {r["fp"]: as_bytes(r["toks"]) for r in toks.join(F.broadcast(wanted), "fp").collect()}


def fit_embedding(pairs: DataFrame, toks: DataFrame, encoder: EncoderConfig, config: TrainConfig = TrainConfig()) -> tuple[TraceEncoder, list[float]]:
    """Train on (category_id, anchor_fp, positive_fp). Gives the model and the loss of every step."""
    rows, traces = _traces_for(pairs, ["category_id", "anchor_fp", "positive_fp"], toks, config)
    model = TraceEncoder(encoder)
    adam, order, log = Adam(model.params, config.rate), np.random.default_rng(config.seed), []
    for _ in range(config.epochs):
        at = order.permutation(len(rows))
        for i in range(0, len(at), config.batch):
            part = [rows[k] for k in at[i : i + config.batch]]
            if len(part) < 2:
                continue
            loss, grads = contrastive_step(model, [traces[r["anchor_fp"]] for r in part], [traces[r["positive_fp"]] for r in part], [r["category_id"] for r in part], config)
            adam.step(grads)
            log.append(loss)
    return model, log


def fit_reranker(triplets: DataFrame, toks: DataFrame, encoder: EncoderConfig, config: TrainConfig = TrainConfig(), use_marker: bool = True) -> tuple[CrossEncoder, list[float]]:
    """Train on (anchor_fp, positive_fp, negative_fp), with weights of its own."""
    rows, traces = _traces_for(triplets, ["anchor_fp", "positive_fp", "negative_fp"], toks, config)
    model = CrossEncoder(encoder, use_marker=use_marker)
    adam, order, log = Adam(model.params, config.rate), np.random.default_rng(config.seed + 1), []
    for _ in range(config.epochs):
        at = order.permutation(len(rows))
        for i in range(0, len(at), config.batch):
            part = [rows[k] for k in at[i : i + config.batch]]
            loss, grads = triplet_step(model, *[[traces[r[c]] for r in part] for c in ("anchor_fp", "positive_fp", "negative_fp")])
            adam.step(grads)
            log.append(loss)
    return model, log


def token_batches(rows: DataFrame, toks: DataFrame, names: tuple[str, ...], config: TrainConfig) -> DataFrame:
    """(batch, turn, category_id, a trace's tokens per name): every drawn row with its traces, dealt to batches; `turn` is the step of an epoch that reads the batch.

    rows name traces as anchor_fp, positive_fp and so on. Written, sorted by turn, so that a step scans its own part.
    """
    dealt = batches(rows, config.batch, config.seed).select("batch", F.pmod("batch", F.lit(config.task_steps)).cast("int").alias("turn"), "category_id", *[f"{n}_fp" for n in names])
    for n in names:
        dealt = dealt.join(toks.select(F.col("fp").alias(f"{n}_fp"), F.col("toks").alias(n)), f"{n}_fp")
    return written(dealt.select("batch", "turn", "category_id", *names).repartition("batch").sortWithinPartitions("turn", "batch"), "train-batches")


def _on_tasks(model, remade: Callable, step: Callable, rows: DataFrame, config: TrainConfig, steps: int, partial_sums: int = 16) -> list[float]:
    """Move the model by `steps` steps, each over the batches of its turn (all rows where there is no turn). Gives the loss of every step.

    Each step broadcasts the weights and every task adds up the gradients of its batches; a second round adds
    those up to `partial_sums` rows, so what reaches the driver grows with the model alone.
    """
    adam, log = Adam(model.params, config.rate), []
    spark = rows.sparkSession

    def summed(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: Arrays = {}
        loss = n = 0.0
        for b in it:
            for r in b.to_pylist():
                for k, g in restore(r["grads"]).items():
                    total[k] = total.get(k, 0) + g
                loss, n = loss + r["loss"], n + r["n"]
        if n:
            yield pa.RecordBatch.from_pydict({"grads": [dump(total)], "loss": [loss], "n": [n]})

    for at in range(steps):
        shared = spark.sparkContext.broadcast(dump(model.params))

        def run(it: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            own = remade(restore(shared.value))
            total: Arrays = {}
            loss = n = 0.0
            held: list[dict] = []

            def add(batch: list[dict]) -> None:
                nonlocal loss, n
                found = step(own, batch)
                if found is not None:
                    loss, n = loss + found[0], n + 1
                    for k, g in found[1].items():
                        total[k] = total.get(k, 0) + g

            for b in it:
                for r in b.to_pylist():
                    if held and held[-1]["batch"] != r["batch"]:
                        add(held)
                        held = []
                    held.append(r)
            if held:
                add(held)
            if n:
                yield pa.RecordBatch.from_pydict({"grads": [dump(total)], "loss": [loss], "n": [n]})

        turn = rows.where(F.col("turn") == at % config.task_steps) if "turn" in rows.columns else rows
        own_rows = turn.repartition("batch").sortWithinPartitions("batch")
        shape = "grads binary, loss double, n double"
        got = own_rows.mapInArrow(run, shape).repartition(partial_sums).mapInArrow(summed, shape).collect()
        total: Arrays = {}
        loss = n = 0.0
        for r in got:
            for k, g in restore(r["grads"]).items():
                total[k] = total.get(k, 0) + g
            loss, n = loss + r["loss"], n + r["n"]
        if n:
            adam.step({k: g / n for k, g in total.items()})
            log.append(loss / n)
        shared.unpersist()
    return log


def fit_embedding_on_tasks(batches: DataFrame, encoder: EncoderConfig, config: TrainConfig = TrainConfig(), steps: int = 5) -> tuple[TraceEncoder, list[float]]:
    """Synchronous data-parallel training on (batch, category_id, anchor, positive), anchor and positive being token arrays."""
    model = TraceEncoder(encoder)

    def step(own: TraceEncoder, rows: list[dict]):
        if len(rows) < 2:
            return None
        return contrastive_step(own, [as_bytes(r["anchor"]) for r in rows], [as_bytes(r["positive"]) for r in rows], [r["category_id"] for r in rows], config)

    return model, _on_tasks(model, lambda params: TraceEncoder(encoder, params), step, batches, config, steps)


def fit_reranker_on_tasks(batches: DataFrame, encoder: EncoderConfig, config: TrainConfig = TrainConfig(), steps: int = 5, use_marker: bool = True) -> tuple[CrossEncoder, list[float]]:
    """The same for the reranker, on (batch, anchor, positive, negative)."""
    model = CrossEncoder(encoder, use_marker=use_marker)

    def step(own: CrossEncoder, rows: list[dict]):
        return triplet_step(own, *[[as_bytes(r[c]) for r in rows] for c in ("anchor", "positive", "negative")])

    return model, _on_tasks(model, lambda params: CrossEncoder(encoder, params, use_marker), step, batches, config, steps)


def loss_table(spark: SparkSession, logs: dict[str, list[float]]) -> DataFrame:
    """(model, step, loss): the logs of fits, a row per step."""
    return spark.createDataFrame([(name, i, float(x)) for name, log in logs.items() for i, x in enumerate(log)], "model string, step int, loss double")


def embed_all(toks: DataFrame, model: TraceEncoder, batch: int = 256, scaled: bool = True) -> DataFrame:
    """(fp, vec): vectors of distinct traces (fp, toks), of length 1 unless scaled=False, a pass over them."""
    config = model.config
    shared = toks.sparkSession.sparkContext.broadcast(dump(model.params))

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = TraceEncoder(config, restore(shared.value))
        for b in it:
            rows = [as_bytes(t) for t in b.column("toks").to_pylist()]
            order = sorted(range(len(rows)), key=lambda i: len(rows[i]))  # rows of like length together
            out: list = [None] * len(rows)
            for i in range(0, len(order), batch):
                at = order[i : i + batch]
                for k, v in zip(at, (unit if scaled else np.asarray)(own.forward([rows[k] for k in at], keep=False)[0]).astype(np.float32), strict=True):
                    out[k] = v
            yield pa.RecordBatch.from_arrays([b.column("fp"), pa.array(out, pa.list_(pa.float32()))], ["fp", "vec"])

    return toks.select("fp", "toks").mapInArrow(run, "fp string, vec array<float>")


def rescore(pairs: DataFrame, toks: DataFrame, model: CrossEncoder, batch: int = 128) -> DataFrame:
    """pairs (q_fp, c_fp, …) with `rerank`, the pairwise model's score. Candidates of a query come to one task, in the query's order."""
    config, marker = model.encoder.config, model.use_marker
    shared = pairs.sparkSession.sparkContext.broadcast(dump(model.params))
    side = lambda n: toks.select(F.col("fp").alias(f"{n}_fp"), F.col("toks").alias(f"{n}_toks"))
    known = pairs.select("q_fp", "c_fp").distinct().join(side("q"), "q_fp").join(side("c"), "c_fp")

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = CrossEncoder(config, restore(shared.value), marker)
        for b in it:
            rows = [(as_bytes(q), as_bytes(c)) for q, c in zip(b.column("q_toks").to_pylist(), b.column("c_toks").to_pylist(), strict=True)]
            out = np.concatenate([own.forward(rows[i : i + batch], keep=False)[0] for i in range(0, len(rows), batch)]) if rows else np.zeros(0)
            yield pa.RecordBatch.from_arrays([b.column("q_fp"), b.column("c_fp"), pa.array(out, pa.float64())], ["q_fp", "c_fp", "rerank"])

    return pairs.join(known.mapInArrow(run, "q_fp string, c_fp string, rerank double"), ["q_fp", "c_fp"])
