"""Quality classifier: hashed word n-gram logistic regression, trained with
follow-the-regularised-leader updates and scored as sparse dot products.

Tokens are runs of word characters or runs of punctuation, so marks that stick
to a word become features of their own. Unigrams and bigrams are hashed into
`2**bits` slots. Repetition, which no single n-gram shows, has slots as well: the
share of tokens equal to the one or two places before, and the share of bigrams
that came before, in tenths. A text is the set of its slots, scaled to unit
length. Only the text is an input of the score.

Defined results: a null or empty text has no features and gets the model's
bias; without labelled rows (or with an empty table) the model is all zero and
every score is 0.5; labels outside 0 and 1, null ids and null labels are not
learnt from; an id that several rows have is learnt from once, with its least
text; repeated rows are scored each on its own; all columns pass through
`score_documents` but those that have the names of its results, which the
results replace.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from partnet.llm.common import drop_kept, give_back, map_rows, tidy

TOKENS = re.compile(r"\w+|[^\w\s]+").findall
CACHE_LIMIT = 100_000
MIX = np.uint64(0x9E3779B97F4A7C15)
#: above every token hash
REPEATS = np.uint64(1 << 40)


@dataclass(frozen=True)
class QualityConfig:
    """max_train_rows bounds the labelled sample the model is fitted on (whole texts, chosen by a hash of the id).

    Passes over the sample go on until about `updates` examples were seen.
    """

    bits: int = 18
    max_train_rows: int = 6_000
    updates: int = 18_000
    alpha: float = 1.0
    beta: float = 1.0
    l1: float = 0.01
    l2: float = 0.1


class NgramHasher:
    """Text to sorted distinct feature slots. Token hashes are cached up to a fixed number."""

    def __init__(self, bits: int):
        self.mask = np.uint64((1 << bits) - 1)
        self.shift = np.uint64(64 - bits)
        self.seen: dict[str, int] = {}

    def token_hashes(self, text: str) -> np.ndarray:
        seen, out = self.seen, []
        for token in TOKENS(text):
            h = seen.get(token)
            if h is None:
                if len(seen) >= CACHE_LIMIT:
                    seen.clear()
                h = seen[token] = zlib.crc32(token.encode("utf-8", "surrogatepass"))
            out.append(h)
        return np.array(out, dtype=np.uint64)

    def slots(self, text: str | None) -> np.ndarray:
        if not text:
            return np.empty(0, dtype=np.int32)
        h = self.token_hashes(text)
        if not h.size:
            return np.empty(0, dtype=np.int32)
        with np.errstate(over="ignore"):
            one = (h + np.uint64(1)) * MIX
            two = np.unique((h[:-1] * np.uint64(0xC2B2AE3D27D4EB4F) + h[1:] + np.uint64(7)) * MIX)
            shares = [np.mean(h[gap:] == h[:-gap]) if h.size > gap else 0.0 for gap in (1, 2)] + [1 - two.size / max(1, h.size - 1)]
            repeats = (np.array([100 * k + int(10 * x) for k, x in enumerate(shares)], dtype=np.uint64) + REPEATS) * MIX
        return np.unique(np.concatenate([one, two, repeats]) >> self.shift).astype(np.int32)


def ftrl_fit(examples: list[tuple[int, np.ndarray]], config: QualityConfig) -> np.ndarray:
    """Weights by slot, the bias last. Per-coordinate FTRL-proximal over passes in the given order.

    Both labels weigh the same in sum, so that a rare label moves the boundary as much as a common one.
    """
    size = (1 << config.bits) + 1
    z, n, w = np.zeros(size), np.zeros(size), np.zeros(size)
    ones = sum(label for label, _ in examples)
    weight = {1: len(examples) / max(1, 2 * ones), 0: len(examples) / max(1, 2 * (len(examples) - ones))}
    for _ in range(-(-config.updates // max(1, len(examples)))):
        for label, slots in examples:
            at = np.append(slots, size - 1)
            x = np.full(at.size, 1.0 / np.sqrt(max(1, slots.size)))
            x[-1] = 1.0
            zi, ni = z[at], n[at]
            wi = np.where(np.abs(zi) <= config.l1, 0.0, -(zi - np.sign(zi) * config.l1) / ((config.beta + np.sqrt(ni)) / config.alpha + config.l2))
            g = (1.0 / (1.0 + np.exp(-np.clip(wi @ x, -35, 35))) - label) * x * weight[label]
            sigma = (np.sqrt(ni + g * g) - np.sqrt(ni)) / config.alpha
            z[at] += g - sigma * wi
            n[at] += g * g
    live = np.abs(z) > config.l1
    w[live] = -(z[live] - np.sign(z[live]) * config.l1) / ((config.beta + np.sqrt(n[live])) / config.alpha + config.l2)
    return w.astype(np.float32)


def is_held_out(doc_id: Column) -> Column:
    """True for the third of the ids that labels are never learnt from."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % 3 == 1, F.lit(False))


def learning_labels(labels: DataFrame) -> DataFrame:
    """(doc_id, label): one row for each labelled id outside the held-out third."""
    usable = F.col("doc_id").isNotNull() & F.col("quality").isin(0, 1) & ~is_held_out(F.col("doc_id"))
    return labels.where(usable).groupBy("doc_id").agg(F.max("quality").cast("int").alias("label"))


def fit_quality(documents: DataFrame, labels: DataFrame, config: QualityConfig = QualityConfig()) -> np.ndarray:
    """Fits on at most config.max_train_rows labelled rows outside the held-out third.

    Features are made in parallel; one task then runs the ordered updates on the bounded sample.
    """
    chosen = learning_labels(labels).select("doc_id", "label", F.xxhash64("doc_id").alias("turn")).orderBy("turn", "doc_id").limit(config.max_train_rows)
    once = documents.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").groupBy("turn", "doc_id", "label").agg(F.min("text").alias("text"))
    sample = once.select("turn", "label", "text")
    bits = config.bits

    def start():
        hasher = NgramHasher(bits)

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            rows = [hasher.slots(x) for x in batch["text"].to_pylist()]
            return pa.RecordBatch.from_arrays([batch["turn"], batch["label"], pa.array([x.tobytes() for x in rows], pa.binary())], ["turn", "label", "slots"])

        return step

    features = map_rows(sample, start, "turn long, label int, slots binary")

    def train(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = []
        for batch in batches:
            rows += zip(batch["turn"].to_pylist(), batch["slots"].to_pylist(), batch["label"].to_pylist(), strict=True)
        rows.sort()
        fitted = ftrl_fit([(y, np.frombuffer(x, dtype=np.int32)) for _, x, y in rows], config)
        yield pa.RecordBatch.from_arrays([pa.array([fitted.tobytes()], pa.binary())], ["weights"])

    fitted = features.repartition(1).mapInArrow(tidy(train), "weights binary").collect()
    return np.frombuffer(bytes(fitted[0]["weights"]), dtype=np.float32) if fitted else np.zeros((1 << bits) + 1, dtype=np.float32)


def score_text(weights: np.ndarray, hasher: NgramHasher, text: str | None) -> float:
    slots = hasher.slots(text)
    dot = float(weights[slots].sum(dtype=np.float64)) / np.sqrt(max(1, slots.size)) + float(weights[-1])
    return float(1.0 / (1.0 + np.exp(-np.clip(dot, -35, 35))))


def score_documents(documents: DataFrame, weights: np.ndarray, config: QualityConfig = QualityConfig(), names: tuple[str, str] = ("score", "predicted")) -> DataFrame:
    """Adds score (double) and predicted (int), under the given names. The weights have a fixed size, so they are broadcast."""
    shared, bits = documents.sparkSession.sparkContext.broadcast(weights), config.bits

    @F.pandas_udf("double")
    def scored(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        drop_kept()
        hasher = NgramHasher(bits)
        for texts in parts:
            yield pd.Series([score_text(shared.value, hasher, x) for x in texts], dtype="float64")
        hasher.seen.clear()
        give_back()

    return documents.withColumn(names[0], scored("text")).withColumn(names[1], (F.col(names[0]) >= 0.5).cast("int"))
