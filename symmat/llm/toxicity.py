"""Document toxicity by multiple-instance learning: sentences are scored, a noisy-or combines them into the document.

A sentence's features are its words and the beginnings of its words (4 to 7 bytes), lower-cased in A-Z and hashed into
2**18 buckets; its probability is a logistic function of the sum of their weights. A document's probability is
1 - prod(1 - p) over its sentences. Weights are learned from document labels alone, by stochastic gradient on the
noisy-or likelihood; each document's gradient goes to its sentences in proportion to what they contribute, so the
sentences that make a document toxic are found without sentence labels.

Fitting uses at most ``FIT_ROWS`` labelled documents, and of these, in the same order by a hash of the doc_id, no more than
fit into ``FIT_BYTES``; only they reach the one executor task that fits, so its memory is bounded. The weights, 1 MB, are broadcast. Scoring covers every sentence of every text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ._common import WordHasher, chunks, utf8, word_spans

BUCKETS_LOG2 = 18
PREFIXES = (4, 5, 6, 7)
#: Most labelled documents used for fitting, and most bytes of their texts held at once.
FIT_ROWS, FIT_BYTES = 16_000, 96 << 20
EPOCHS, RATE, DECAY = 8, 1.0, 1e-6
#: A feature counts if at least so many of the fitted documents have it; CALM keeps the first steps of rare ones small.
#: It is the value of CALM that 14,000 documents get; fewer take proportionally less.
LEAST_DOCS, CALM = 10, 10.0
THRESHOLD = 0.7
#: Small tables get more epochs, until the fit has made so many steps.
LEAST_STEPS = 60

_BLANK = np.zeros(256, bool)
_BLANK[list(range(0x21))] = True
_BLANK[[ord(c) for c in ".,;:!?\"'()[]{}<>*%$&|#+=/\\-_~`^@"]] = True
_STOP = np.zeros(256, bool)
_STOP[[ord(c) for c in ".!?\n"]] = True


def features(flat: np.ndarray, offsets: np.ndarray, hasher: WordHasher) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Feature buckets (words x features, -1 where a word is too short), each word's sentence, each sentence's text and its first byte.

    Sentences end at . ! ? or a line break; only those with a word count. Sentence numbers run over all texts.
    """
    start, end, first = word_spans(flat, offsets, _BLANK)
    if not len(start):
        return np.zeros((0, 1 + len(PREFIXES)), np.int32), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    text_of = np.repeat(np.arange(len(offsets) - 1), np.diff(first))
    ends = np.concatenate([[0], np.cumsum(_STOP[flat])])[start]
    fresh = np.ones(len(start), bool)
    fresh[1:] = (ends[1:] != ends[:-1]) | (text_of[1:] != text_of[:-1])
    sentence = np.cumsum(fresh) - 1
    prefix = hasher.prefix(flat)
    out = np.full((len(start), 1 + len(PREFIXES)), -1, np.int32)
    shift = np.uint64(64 - BUCKETS_LOG2)
    out[:, 0] = (hasher.of(prefix, start, end) >> shift).astype(np.int32)
    for k, n in enumerate(PREFIXES, 1):
        long = np.flatnonzero(end - start > n)
        h = hasher.of(prefix, start[long], start[long] + n) * np.uint64(0x9E3779B97F4A7C15 + 2 * k)
        out[long, k] = (h >> shift).astype(np.int32)
    return out, sentence, text_of[fresh], start[fresh]


def sentence_logits(weights: np.ndarray, f: np.ndarray, sentence: np.ndarray, n: int) -> np.ndarray:
    """weights has one more cell than buckets: the last is the bias; -1 must read 0, so a zero cell is put before it."""
    padded = np.append(weights[:-1], 0.0).astype(np.float32)
    word = padded[f].sum(axis=1)
    return np.bincount(sentence, word, n) + weights[-1]


def _noisy_or(logits: np.ndarray, doc: np.ndarray, n: int) -> np.ndarray:
    """log prod(1 - p) per document: sums of -softplus(logit)."""
    return -np.bincount(doc, np.logaddexp(0.0, logits), n)


def fit(texts: pa.Array, toxic: np.ndarray, epochs: int = EPOCHS, rate: float = RATE, seed: int = 5) -> np.ndarray:
    """Weights (buckets + bias) from whole labelled texts, by AdaGrad over batches of documents in a seeded order."""
    hasher = WordHasher()
    flat, offsets = utf8(texts)
    rng = np.random.default_rng(seed)
    weights = np.zeros((1 << BUCKETS_LOG2) + 1)
    weights[-1] = -6.0
    square = np.full(len(weights), max(1e-3, CALM * len(toxic) / 14_000))
    spans = list(chunks(offsets, 1 << 18))
    docs_with = np.zeros(len(weights), np.int64)
    for i, j in spans:
        f, sentence, doc, _ = features(flat[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], hasher)
        pairs = np.unique((doc[sentence][:, None] * len(weights) + f)[f >= 0])
        docs_with += np.bincount(pairs % len(weights), minlength=len(weights))
    known = docs_with >= min(LEAST_DOCS, max(1, len(toxic) // 20))
    known[-1] = True
    for _ in range(max(epochs, -(-LEAST_STEPS // max(1, len(spans))))):
        for s in rng.permutation(len(spans)):
            i, j = spans[s]
            f, sentence, doc, _ = features(flat[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], hasher)
            if not len(doc):
                continue
            y = toxic[i:j].astype(float)
            z = sentence_logits(weights, f, sentence, len(doc))
            none = _noisy_or(z, doc, j - i)
            some = -np.expm1(none)
            # d log-likelihood / d logit of a sentence: p * (1 - p_doc) / p_doc where toxic, -p where not
            pull = np.where(y > 0, np.exp(none) / np.maximum(some, 1e-9), -1.0)[doc]
            g = np.clip(pull / (1 + np.exp(np.minimum(-z, 60.0))), -1, 1)
            at = f[f >= 0]
            grad = np.bincount(at, np.broadcast_to(g[sentence][:, None], f.shape)[f >= 0], len(weights))
            grad[-1] = g.sum() * 0.05
            grad -= DECAY * weights
            grad *= known
            square += grad * grad
            weights += rate * grad / np.sqrt(square)
    return weights


def _fit_task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held = [b for b in batches if len(b)]
    if not held:
        return
    rows = pa.Table.from_batches(held)
    weights = fit(rows.column("text").combine_chunks(), rows.column("toxic").to_numpy())
    yield pa.RecordBatch.from_arrays([pa.array([weights.astype(np.float32).tobytes()], pa.binary())], names=["weights"])


def train(docs: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS, fit_bytes: int = FIT_BYTES) -> np.ndarray:
    """Weights learned from the labelled rows whose crc32(doc_id) mod 3 is not 1, at most ``fit_rows`` of them and ``fit_bytes`` of text; all zero without any.

    A null label or doc_id is none. A doc_id with two labels counts as toxic; of several texts under one doc_id, the one of
    smallest hash is used.
    """
    free = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(3)) != 1
    marked = labels.where(F.col("toxic").isin(0, 1) & free).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    marked = marked.orderBy(F.xxhash64("doc_id"), "doc_id").limit(fit_rows)
    texts = docs.select(F.col("doc_id"), F.col("text").cast("string").alias("text"))
    rows = texts.join(F.broadcast(marked), "doc_id").withColumn("size", F.octet_length(F.coalesce("text", F.lit("")))).withColumn("t", F.xxhash64("text"))  # at most fit_rows of two numbers each
    first = rows.groupBy("doc_id").agg(F.min(F.struct("t", "size")).alias("x")).select("doc_id", "x.t", "x.size").where(F.col("size") <= fit_bytes)
    upto = F.sum("size").over(Window.orderBy(F.xxhash64("doc_id"), "doc_id"))  # over at most fit_rows rows of three numbers
    chosen = first.withColumn("upto", upto).where(F.col("upto") <= fit_bytes).select("doc_id", "t")
    texts = rows.join(F.broadcast(chosen), ["doc_id", "t"]).dropDuplicates(["doc_id"])
    fitted = texts.select("doc_id", "text", "toxic").repartition(1).sortWithinPartitions("doc_id").select("text", "toxic").mapInArrow(_fit_task, "weights binary").first()
    if fitted is None:
        empty = np.zeros((1 << BUCKETS_LOG2) + 1)
        empty[-1] = -6.0
        return empty
    return np.frombuffer(fitted.weights, np.float32)


def _scorer(shared, keep_below: float | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher, weights = WordHasher(), shared.value
        for batch in batches:
            flat, offsets = utf8(batch.column("text"))
            for i, j in chunks(offsets):
                part = flat[offsets[i] : offsets[j]]
                at = offsets[i : j + 1] - offsets[i]
                f, sentence, doc, first = features(part, at, hasher)
                z = sentence_logits(weights, f, sentence, len(doc))
                score = -np.expm1(_noisy_or(z, doc, j - i))
                if keep_below is not None:
                    yield batch.slice(i, j - i).filter(pa.array(score < keep_below))
                    continue
                worst, where = np.full(j - i, -np.inf), np.full(j - i, -1, np.int64)
                np.maximum.at(worst, doc, z)
                hit = np.flatnonzero(z == worst[doc])[::-1]
                where[doc[hit]] = first[hit] - at[doc[hit]]
                found = np.bincount(doc, z > 0, j - i).astype(np.int64)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(i, j - i), pa.array(score), pa.array(found), pa.array(where)], names=["doc_id", "score", "n_sentences", "worst_at"])

    return run


def score(docs: DataFrame, weights: np.ndarray, threshold: float = THRESHOLD) -> DataFrame:
    """A row per row of ``docs``: doc_id, held_out, score, predicted, n_sentences (sentences likelier toxic than not), worst_at (byte where the worst one begins; -1 without words).

    A null, empty or wordless text has no sentence and score 0. A null doc_id is not held out.
    """
    shared = docs.sparkSession.sparkContext.broadcast(weights)
    scored = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(_scorer(shared, None), "doc_id long, score double, n_sentences long, worst_at long")
    held = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(3)) == 1, F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"), "n_sentences", "worst_at")


def drop_toxic(docs: DataFrame, weights: np.ndarray, threshold: float = THRESHOLD) -> DataFrame:
    """``docs`` without the rows that score ``threshold`` or more; one narrow pass, all columns stay."""
    shared = docs.sparkSession.sparkContext.broadcast(weights)
    return docs.mapInArrow(_scorer(shared, threshold), docs.schema)
