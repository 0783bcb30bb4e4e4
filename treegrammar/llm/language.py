"""Language ID by a bidirectional gated recurrent network over bytes, trained in numpy.

The network reads the UTF-8 bytes of a text in windows of ``WINDOW`` bytes, labels every byte, and the document's
probabilities are the mean over all its bytes. It is trained by backpropagation through time on a bounded sample of
documents that are not held out: about ``DOCS`` of each language, chosen by a hash of their id, and windows from all
over their texts.

Defined results: a text that is null or holds no letter is ``und`` with score 0; so is every text if no row has a
language to learn from. Texts of any length are read whole; ties go to the language first in order; repeated rows are labelled
alike; extra columns are ignored. lang, source and doc_id are never inputs of a prediction.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treegrammar.llm.holdout import held_out
from treegrammar.llm.recurrent import Adam, BiGru

WINDOW, HIDDEN, PAD = 64, 8, 256
#: Documents of a language in the sample, about; windows of a document; bytes of a document that the sample may hold.
DOCS, WINDOWS = 300, 12
STEPS, BATCH, RATE = 350, 192, 0.02
_LETTER = re.compile(r"[^\W\d_]")


def has_letter(text: str) -> bool:
    """Whether a text holds a letter: numerals such as superscripts and fractions are none."""
    return any(m[0].isalpha() for m in _LETTER.finditer(text))


def windows(data: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """All bytes of the texts, each padded to whole windows: symbols (windows, WINDOW), and the text of each window."""
    n = np.array([-(-len(d) // WINDOW) for d in data], np.int64)
    flat = np.full(int(n.sum()) * WINDOW, PAD, np.int16)
    at = np.concatenate([[0], np.cumsum(n)]) * WINDOW
    for d, start in zip(data, at[:-1].tolist(), strict=True):
        flat[start : start + len(d)] = np.frombuffer(d, np.uint8)
    return flat.reshape(-1, WINDOW), np.repeat(np.arange(len(data)), n)


class LanguageModel:
    def __init__(self, languages: list[str]):
        self.languages = languages
        self.net = BiGru(PAD + 1, HIDDEN, max(1, len(languages)))

    def train(self, texts: list[str], langs: list[str], steps: int = STEPS, seed: int = 5) -> list[float]:
        rng = np.random.default_rng(seed)
        data = [t.encode("utf-8", "replace") for t in texts]
        ids, of = windows(data)
        label = np.array([self.languages.index(x) for x in langs])[of] if len(of) else np.empty(0, int)
        by = [np.flatnonzero(label == k) for k in range(len(self.languages))]
        by = [x for x in by if len(x)]
        if not by:
            return []
        adam, losses = Adam(self.net.p, RATE), []
        for step in range(steps):
            adam.rate = RATE * (1 - step / steps) + 0.002
            pick = np.concatenate([rng.choice(x, BATCH // len(by) + 1) for x in by])
            x = ids[pick].T.astype(np.int64)
            y = np.broadcast_to(label[pick], x.shape)
            loss, grads = self.net.gradients(x, np.ascontiguousarray(y), (x != PAD).astype(np.float32))
            adam.step(grads)
            losses.append(loss)
        return losses

    def probabilities(self, texts: list[str]) -> np.ndarray:
        """Mean class probabilities over all bytes of each text."""
        data = [t.encode("utf-8", "replace") for t in texts]
        ids, of = windows(data)
        total = np.zeros((len(data), len(self.languages)))
        for at in range(0, len(ids), 2048):
            x = np.ascontiguousarray(ids[at : at + 2048].T)
            logits = self.net.logits(self.net.states(x))
            np.exp(logits, out=logits)
            logits /= logits.sum(axis=-1, keepdims=True)
            logits *= (x != PAD)[..., None]
            np.add.at(total, of[at : at + 2048], logits.sum(axis=0))
        return total / np.maximum(1, np.array([len(d) for d in data]))[:, None]

    def predict(self, texts: list[str | None]) -> list[tuple[str, float]]:
        out: list[tuple[str, float]] = [("und", 0.0)] * len(texts)
        live = [i for i, t in enumerate(texts) if t and has_letter(t)] if self.languages else []
        prob = self.probabilities([texts[i] for i in live])
        for i, p in zip(live, prob, strict=True):
            k = int(np.argmax(p))
            out[i] = (self.languages[k], float(min(1.0, max(0.0, p[k]))))
        return out


def fit(spark: SparkSession, docs: DataFrame, docs_each: int = DOCS, windows_each: int = WINDOWS) -> LanguageModel:
    """Train on about ``docs_each`` documents of each language (doc_id, text, lang) and ``windows_each`` windows of each."""
    known = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang")).where(~held_out("doc_id") & F.col("lang").isNotNull())
    sizes = {r["lang"]: r["n"] for r in known.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    if not sizes:
        return LanguageModel([])
    share = F.coalesce(*[F.when(F.col("lang") == k, F.lit(min(1.0, docs_each / n))) for k, n in sizes.items()])
    draw = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)) / F.lit(float(1 << 30))
    rows = known.where((draw < share) & (F.length("text") > 0))
    # Windows from evenly spaced places of the whole text, cut before they leave the executors.
    size = F.length("text")
    cuts = F.transform(F.sequence(F.lit(0), F.lit(windows_each - 1)), lambda k: F.substring("text", (k * size / windows_each).cast("int") + 1, F.lit(WINDOW)))
    got = sorted((r["lang"], r["doc_id"], r["cuts"]) for r in rows.select("lang", "doc_id", F.when(size > WINDOW * windows_each, cuts).otherwise(F.array("text")).alias("cuts")).toLocalIterator())
    texts = [(lang, t) for lang, _, cuts in got for t in cuts if t and has_letter(t)]
    model = LanguageModel(sorted(sizes))
    model.train([t for _, t in texts], [lang for lang, _ in texts])
    return model


def predict(spark: SparkSession, docs: DataFrame, model: LanguageModel) -> DataFrame:
    """doc_id, lang_pred, score of every row (doc_id, text)."""
    shared = spark.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 128):
                part = batch.slice(at, 128)
                got = own.predict(part.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64())], names=["doc_id", "lang_pred", "score"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, lang_pred string, score double")
