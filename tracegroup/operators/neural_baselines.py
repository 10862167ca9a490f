"""Two trained comparison methods: a pairwise model over frame vectors, and a cosine model over package vectors."""

from __future__ import annotations

import numpy as np
from pyspark.ml.feature import Word2Vec
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tracegroup.operators import train
from tracegroup.operators.baselines import traces_of
from tracegroup.operators.bpe import UNKNOWN
from tracegroup.operators.encoder import OWN, EncoderConfig, TraceEncoder
from tracegroup.operators.index import exact_topk
from tracegroup.operators.losses import bce_pair
from tracegroup.operators.nn import Adam, Arrays
from tracegroup.operators.pairs import default_cap, positive_pairs, triplets
from tracegroup.sources.storage import written

SMALL = EncoderConfig(vocab=20_000, token=16, trace=16, frame_encoder="mean")


class PairHead:
    """A learned comparison of two trace vectors: difference, mean and product, weighted place by place and added up."""

    def __init__(self, params: Arrays, width: int, seed: int = 2):
        self.params = params
        if "h.w" not in params:
            params["h.w"] = np.random.default_rng(seed).normal(0, 0.1, (3, width))
            params["h.b"] = np.zeros(1)

    def forward(self, u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, tuple]:
        w = self.params["h.w"]
        return np.abs(u - v) @ w[0] + (u + v) @ w[1] / 2 + (u * v) @ w[2] + self.params["h.b"][0], (u, v)

    def backward(self, d: np.ndarray, cache: tuple, grads: Arrays) -> tuple[np.ndarray, np.ndarray]:
        (u, v), w = cache, self.params["h.w"]
        sign = np.sign(u - v)
        grads["h.w"] = grads.get("h.w", 0) + np.stack([d @ np.abs(u - v), d @ (u + v) / 2, d @ (u * v)])
        grads["h.b"] = grads.get("h.b", 0) + d.sum(keepdims=True)
        d = d[:, None]
        return d * (sign * w[0] + w[1] / 2 + v * w[2]), d * (-sign * w[0] + w[1] / 2 + u * w[2])

    def all_pairs(self):
        """similarity(queries, rows) for a search over all pairs; this head cannot be indexed."""
        w, b = self.params["h.w"].copy(), float(self.params["h.b"][0])

        def similarity(q: np.ndarray, m: np.ndarray) -> np.ndarray:
            out = (q * w[2]) @ m.T + (q @ w[1])[:, None] / 2 + (m @ w[1])[None, :] / 2 + b
            for i in range(len(q)):
                out[i] += np.abs(q[i] - m) @ w[0]
            return out

        return similarity


def pairwise_step(model: TraceEncoder, head: PairHead, anchors: list, positives: list, negatives: list) -> tuple[float, Arrays]:
    n = len(anchors)
    vec, cache = model.forward([*anchors, *positives, *negatives])
    a, p, m = vec[:n], vec[n : 2 * n], vec[2 * n :]
    sp, cp = head.forward(a, p)
    sn, cn = head.forward(a, m)
    loss, dp, dn = bce_pair(sp, sn)
    grads: Arrays = {}
    da1, dpos = head.backward(dp, cp, grads)
    da2, dneg = head.backward(dn, cn, grads)
    model.backward(np.concatenate([da1 + da2, dpos, dneg]), cache, grads)
    return loss, grads


def names_as_tokens(reports: DataFrame, name, most: int) -> tuple[DataFrame, dict[str, int]]:
    """(fp, toks): one id per frame, of the `most` most frequent names of the training part; any other name has a fixed vector of its own, by its hash.

    Ids only bound the table that is trained; the fixed vectors are drawn in the tasks, as the table's are before training.
    """
    old = reports.where("part = 'train'").select(F.explode("frames").alias("f")).select(name(F.col("f")).alias("name")).groupBy("name").agg(F.count("*").alias("n"))
    ids = {r["name"]: i + 2 for i, r in enumerate(old.orderBy(F.desc("n"), "name").limit(most - 2).collect())}
    table = reports.sparkSession.createDataFrame(list(ids.items()) or [("", UNKNOWN)], "name string, id int")
    spread = traces_of(reports).select("fp", F.posexplode_outer("frames").alias("pos", "f")).withColumn("name", name(F.col("f"))).join(table, "name", "left")
    h = F.xxhash64("name")
    own = F.array(F.lit(OWN), F.shiftright(h, 32).cast("int"), (h.bitwiseAND(F.lit(0xFFFFFFFF)) - F.lit(1 << 31)).cast("int"))
    one = F.when(F.col("pos").isNotNull(), F.struct("pos", F.when(F.col("id").isNotNull(), F.array("id")).otherwise(own).alias("t")))
    return spread.groupBy("fp").agg(F.transform(F.sort_array(F.collect_list(one)), lambda x: x["t"]).alias("toks")), ids


def _searched(reports: DataFrame, queries: DataFrame, vectors: DataFrame, k: int, similarity=None) -> DataFrame:
    base = reports.groupBy("fp").agg(F.min("arrival_seq").alias("seq")).join(vectors, "fp").select(F.col("fp").alias("id"), "seq", "vec")
    asked = queries.select(F.col("fp").alias("id")).distinct().join(base, "id")
    return exact_topk(asked, base, k, True, similarity).select(F.col("q_id").alias("q_fp"), F.col("c_id").alias("c_fp"), "score")


def pairwise_frames(reports: DataFrame, queries: DataFrame, k: int = 10, encoder: EncoderConfig = SMALL, config: train.TrainConfig = train.TrainConfig(epochs=2, most_rows=1500)) -> DataFrame:
    """(q_fp, c_fp, score): one vector per frame name, a recurrent network over them, and a learned comparison with every earlier trace."""
    toks, _ = names_as_tokens(reports, lambda f: f, encoder.vocab)
    toks = written(toks, "frame-tokens")
    old = reports.where("part = 'train'")
    drawn = triplets(positive_pairs(old, default_cap(old)), old)
    rows, traces = train._traces_for(drawn, ["anchor_fp", "positive_fp", "negative_fp"], toks, config)
    model = TraceEncoder(encoder)
    head = PairHead(model.params, model.width)
    adam, order = Adam(model.params, config.rate), np.random.default_rng(config.seed)
    for _ in range(config.epochs):
        at = order.permutation(len(rows))
        for i in range(0, len(at), config.batch):
            part = [rows[j] for j in at[i : i + config.batch]]
            _, grads = pairwise_step(model, head, *[[traces[r[c]] for r in part] for c in ("anchor_fp", "positive_fp", "negative_fp")])
            adam.step(grads)
    vectors = written(_raw_vectors(toks, model), "pairwise-vectors")
    return _searched(reports, queries, vectors, k, head.all_pairs())


def _raw_vectors(toks: DataFrame, model: TraceEncoder) -> DataFrame:
    """(fp, vec), not scaled: the learned comparison reads lengths too."""
    return train.embed_all(toks, model, scaled=False)


def package_vectors(reports: DataFrame, queries: DataFrame, k: int = 10, sep: str = ".", encoder: EncoderConfig = SMALL, config: train.TrainConfig = train.TrainConfig(epochs=2, most_rows=1500)) -> DataFrame:
    """(q_fp, c_fp, score): package names get vectors from their neighbours in traces, a recurrent network reads them, cosine compares."""
    package = lambda f: F.when(F.instr(f, sep) > 0, F.substring_index(f, sep, 1)).otherwise(f)
    toks, ids = names_as_tokens(reports, package, encoder.vocab)
    toks = written(toks, "package-tokens")
    old = reports.where("part = 'train'")
    model = TraceEncoder(encoder)
    sentences = traces_of(old).select(F.transform("frames", lambda f: package(f)).alias("s"))
    fitted = Word2Vec(vectorSize=encoder.token, minCount=1, inputCol="s", outputCol="v", seed=1, windowSize=3).fit(sentences)
    for r in fitted.getVectors().where(F.col("word").isin(list(ids)) if len(ids) < 1000 else F.lit(True)).toLocalIterator():
        if r["word"] in ids:
            model.params["e.tokens"][ids[r["word"]]] = r["vector"].toArray()
    drawn = positive_pairs(old, default_cap(old))
    rows, traces = train._traces_for(drawn, ["category_id", "anchor_fp", "positive_fp"], toks, config)
    adam, order = Adam(model.params, config.rate), np.random.default_rng(config.seed)
    for _ in range(config.epochs):
        at = order.permutation(len(rows))
        for i in range(0, len(at), config.batch):
            part = [rows[j] for j in at[i : i + config.batch]]
            if len(part) > 1:
                adam.step(train.contrastive_step(model, [traces[r["anchor_fp"]] for r in part], [traces[r["positive_fp"]] for r in part], [r["category_id"] for r in part], config)[1])
    return _searched(reports, queries, written(train.embed_all(toks, model), "package-vectors"), k)
