"""The whole method: tokens, vectors, nearest earlier traces, pairwise reranking, decision."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tracegroup.functions.frames import pieces as frame_pieces
from tracegroup.operators import bpe, index, pairs, replay, train
from tracegroup.operators.baselines import traces_of
from tracegroup.operators.chronology import index_entries, queries_of
from tracegroup.operators.decide import calibrated, decide
from tracegroup.operators.encoder import CrossEncoder, EncoderConfig, TraceEncoder
from tracegroup.operators.metrics import best_threshold
from tracegroup.sources.storage import written

SMALL = EncoderConfig(vocab=10_000, token=16, frame=12, trace=24)


@dataclass
class TwoStage:
    """Options of the method. reranker=False leaves the second stage out; tokens: bpe, frame or package.

    search: exact, ivf, lsh or sq8. threshold: a fixed one (0 attaches whatever has a candidate, 1 nothing); None takes the best on the validation part.
    """

    encoder: EncoderConfig = SMALL
    training: train.TrainConfig = field(default_factory=lambda: train.TrainConfig(epochs=2, most_rows=1500))
    k: int = 10
    reranker: bool = True
    use_marker: bool = True
    style: str = "camel"
    sep: str | None = "."
    tokens: str = "bpe"
    cap: int | None = None
    search: str = "exact"
    threshold: float | None = None

    def fit(self, reports: DataFrame) -> Fitted:
        """Train on the training part only: vocabulary, pairs and triplets."""
        old = reports.where("part = 'train'")
        cut = (lambda c: frame_pieces(c, self.style, sep=self.sep)) if self.tokens == "bpe" else (lambda c: F.array(c if self.tokens == "frame" else F.split(c, r"\.")[0]))
        frames = old.select(F.explode("frames").alias("frame")).distinct()
        counts = bpe.piece_counts(frames.select(cut(F.col("frame")).alias("pieces")))
        if self.tokens == "bpe":
            model = bpe.train(counts, self.encoder.vocab)
        else:  # a closed vocabulary: one id per name that training has seen
            rows = counts.orderBy(F.desc("n"), "piece").limit(self.encoder.vocab - 2).collect()
            model = bpe.Bpe([], {r["piece"]: i + 2 for i, r in enumerate(rows)})
        traces = traces_of(reports)
        every = traces.select(F.explode("frames").alias("frame")).distinct().select(F.explode(cut(F.col("frame"))).alias("piece")).distinct()
        if self.tokens == "bpe":
            tokens = bpe.encoded(every, model)
        else:
            names = reports.sparkSession.createDataFrame(list(model.vocab.items()) or [("", 0)], "piece string, id int")
            tokens = every.join(names, "piece", "left").select("piece", F.array(F.coalesce("id", F.lit(bpe.UNKNOWN))).alias("tokens"))
        toks = written(train.tokenised(traces, tokens, cut), "trace-tokens")
        cap = self.cap or pairs.default_cap(old)
        drawn = written(pairs.positive_pairs(old, cap), "train-pairs")
        steps = self.training.task_steps * self.training.epochs
        if steps:
            embedding, log = train.fit_embedding_on_tasks(train.token_batches(drawn, toks, ("anchor", "positive"), self.training), self.encoder, self.training, steps)
        else:
            embedding, log = train.fit_embedding(drawn, toks, self.encoder, self.training)
        cross, cross_log = (None, [])
        if self.reranker and steps:
            cross, cross_log = train.fit_reranker_on_tasks(train.token_batches(pairs.triplets(drawn, old), toks, ("anchor", "positive", "negative"), self.training), self.encoder, self.training, steps, self.use_marker)
        elif self.reranker:
            cross, cross_log = train.fit_reranker(pairs.triplets(drawn, old), toks, self.encoder, self.training, self.use_marker)
        vectors = written(train.embed_all(toks, embedding), "trace-vectors")
        return Fitted(self, model, toks, vectors, embedding, cross, log, cross_log)


@dataclass
class Fitted:
    options: TwoStage
    bpe: bpe.Bpe
    toks: DataFrame
    vectors: DataFrame
    embedding: TraceEncoder
    cross: CrossEncoder | None
    log: list[float]
    cross_log: list[float]

    def candidates(self, reports: DataFrame, queries: DataFrame) -> DataFrame:
        """(q_fp, c_fp, score): the k nearest traces that arrived before each query, cosine as the score."""
        first = reports.groupBy("fp").agg(F.min("arrival_seq").alias("seq"))
        base = first.join(self.vectors, "fp").select(F.col("fp").alias("id"), "seq", "vec")
        q = queries.select("fp", "arrival_seq").groupBy("fp").agg(F.min("arrival_seq").alias("seq")).join(self.vectors, "fp").select(F.col("fp").alias("id"), "seq", "vec")
        o = self.options
        if o.search == "ivf":
            centroids, cells = index.ivf_build(base, 16)
            found = index.ivf_topk(q, cells, centroids, o.k, 6)
        elif o.search == "lsh":
            found = index.lsh_topk(q, base, o.k, width=self.embedding.width)
        elif o.search == "sq8":
            found = index.sq8_topk(q, base, o.k)
        else:
            found = index.exact_topk(q, base, o.k)
        return found.select(F.col("q_id").alias("q_fp"), F.col("c_id").alias("c_fp"), "score")

    def outcomes(self, reports: DataFrame, part: str = "test", skip_identical: bool = True) -> DataFrame:
        queries = queries_of(reports, part, skip_identical)
        found = self.candidates(reports, queries)
        if self.cross is not None:
            found = train.rescore(found, self.toks, self.cross).select("q_fp", "c_fp", calibrated(F.col("rerank"), "rerank").alias("score"))
        else:
            found = found.select("q_fp", "c_fp", calibrated(F.col("score"), "embedding").alias("score"))
        found = replay.earlier_pairs(queries, found, index_entries(reports))
        return replay.outcomes(queries, replay.ranked(replay.category_scores(found)))

    def decisions(self, reports: DataFrame) -> DataFrame:
        """Outcomes of the test part with the action, by the option's threshold or the one that is best on the validation part."""
        fixed = self.options.threshold
        if fixed is not None:
            t = reports.sparkSession.range(1).select(F.lit(float(fixed)).alias("threshold"))
        else:
            t = written(best_threshold(self.outcomes(reports, "validation")), "threshold")
        return decide(self.outcomes(reports, "test"), t)
