"""Language identification by a small byte convolutional network, trained in numpy.

Texts are lower-cased and read as UTF-8 bytes in windows of fixed length that cover the whole text (neighbours
overlap by the widest filter less one). A window: byte embedding, filters of several widths, rectifier, maximum
over positions, softmax. A text's probabilities are its windows' means by length.

The network learns from a bounded sample (SAMPLE_ROWS rows per language, by a hash of doc_id, a few windows of
each) of rows with a language whose crc32(doc_id) mod 3 isn't 1. Null texts and texts without a letter are `und`
with score 0; so is every text if nothing could be learned. Ties go to the first language by name.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import append_columns, give_back, slices

WINDOW = 256
EMBED = 4
WIDTHS = (2, 3, 4)
FILTERS = 12
SPAN = max(WIDTHS)
SAMPLE_ROWS = 400
SAMPLE_WINDOWS = 4
SALTS = 32
EPOCHS = 6
UNKNOWN = "und"

_LETTER = regex.compile(r"\p{L}")


@dataclass
class Network:
    langs: list[str]
    embed: np.ndarray  # 256 x EMBED
    filters: np.ndarray  # filters x (SPAN * EMBED), offset-major; narrower filters end in zeros
    bias: np.ndarray
    dense: np.ndarray  # filters x languages
    dense_bias: np.ndarray

    def pooled(self, windows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Pooled features, the inputs (SPAN*EMBED, n, positions), and the raw responses."""
        n, length = windows.shape
        places = length - SPAN + 1
        embedded = np.take(self.embed.T, windows, axis=1)
        inputs = np.empty((SPAN * EMBED, n, places), np.float32)
        for k in range(SPAN):
            inputs[k * EMBED : (k + 1) * EMBED] = embedded[:, :, k : k + places]
        raw = (self.filters @ inputs.reshape(SPAN * EMBED, -1)).reshape(-1, n, places)
        return np.maximum(raw.max(2).T + self.bias, 0), inputs, raw

    def probabilities(self, windows: np.ndarray) -> np.ndarray:
        logits = self.pooled(windows)[0] @ self.dense + self.dense_bias
        e = np.exp(logits - logits.max(1, keepdims=True))
        return e / e.sum(1, keepdims=True)


def _mask() -> np.ndarray:
    rows = [np.repeat(np.arange(SPAN) < w, EMBED) for w in WIDTHS for _ in range(FILTERS)]
    return np.array(rows, np.float32)


def windows_of(raw: bytes) -> np.ndarray:
    """Windows (n, WINDOW) over all bytes of a text, the last one padded with byte 0."""
    step = WINDOW - SPAN + 1
    n = max(1, -(-(len(raw) - SPAN + 1) // step))
    padded = np.zeros((n - 1) * step + WINDOW, np.uint8)
    padded[: len(raw)] = np.frombuffer(raw, np.uint8)
    return np.lib.stride_tricks.as_strided(padded, (n, WINDOW), (step, 1))


def fit(texts: list[str], labels: list[str], epochs: int = EPOCHS, seed: int = 11) -> Network | None:
    """Trains on windows; each epoch shortens some of them at random, so that short texts are known too."""
    langs = sorted(set(labels))
    if not langs:
        return None
    rng = np.random.default_rng(seed)
    mask = _mask()
    total = len(mask)
    net = Network(
        langs,
        rng.normal(0, 0.5, (256, EMBED)).astype(np.float32),
        (rng.normal(0, 0.3, (total, SPAN * EMBED)) * mask).astype(np.float32),
        np.zeros(total, np.float32),
        rng.normal(0, 0.2, (total, len(langs))).astype(np.float32),
        np.zeros(len(langs), np.float32),
    )
    x, y = [], []
    for text, lang in zip(texts, labels):
        raw = text.lower().encode()[:WINDOW]
        x.append(raw)
        y.append(langs.index(lang))
    target = np.array(y)
    params = [net.embed, net.filters, net.bias, net.dense, net.dense_bias]
    first, second = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
    step, batch = 0, 64
    for epoch in range(epochs):
        order = rng.permutation(len(x))
        for at in range(0, len(order), batch):
            pick = order[at : at + batch]
            w = np.zeros((len(pick), WINDOW), np.uint8)
            for i, k in enumerate(pick):
                size = len(x[k]) if rng.random() < 0.4 else int(rng.integers(min(16, len(x[k])), len(x[k]) + 1))
                w[i, :size] = np.frombuffer(x[k][:size], np.uint8)
            feats, inputs, raw = net.pooled(w)
            logits = feats @ net.dense + net.dense_bias
            e = np.exp(logits - logits.max(1, keepdims=True))
            d_logits = e / e.sum(1, keepdims=True)
            d_logits[np.arange(len(pick)), target[pick]] -= 1
            d_logits /= len(pick)
            d_feats = (d_logits @ net.dense.T) * (feats > 0)
            where = raw.argmax(2)  # filters x windows
            rows = np.arange(len(pick))[None, :]
            seen = inputs[:, rows, where]  # inputs x filters x windows
            d_filters = np.einsum("ifn,nf->fi", seen, d_feats) * mask
            d_inputs = d_feats.T[:, :, None] * net.filters[:, None, :]  # filters x windows x inputs
            d_embed = np.zeros_like(net.embed)
            for k in range(SPAN):
                np.add.at(d_embed, w[np.broadcast_to(rows, where.shape), where + k], d_inputs[:, :, k * EMBED : (k + 1) * EMBED])
            grads = [d_embed, d_filters, d_feats.sum(0), feats.T @ d_logits, d_logits.sum(0)]
            step += 1
            rate = 0.01 * (1 - 0.8 * epoch / epochs)
            for p, g, m, v in zip(params, grads, first, second):
                m += 0.1 * (g - m)
                v += 0.001 * (g * g - v)
                p -= (rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
    return net


def predict(net: Network | None, texts: list[str | None]) -> tuple[list[str], list[float]]:
    langs, scores = [UNKNOWN] * len(texts), [0.0] * len(texts)
    if net is None:
        return langs, scores
    known = [k for k, t in enumerate(texts) if t and _LETTER.search(t)]
    for i, j in slices([texts[k] for k in known], 1 << 19):
        part = known[i:j]
        raws = [texts[k].lower().encode() for k in part]
        wins = [windows_of(r) for r in raws]
        counts = np.array([len(w) for w in wins])
        flat = np.concatenate(wins)
        probs = np.concatenate([net.probabilities(flat[a : a + 128]) for a in range(0, len(flat), 128)]).astype(np.float64)
        starts = np.concatenate([[0], np.cumsum(counts)[:-1]])
        weight = np.full(len(flat), float(WINDOW))
        step = WINDOW - SPAN + 1
        weight[starts + counts - 1] = [max(1, len(r) - (c - 1) * step) for r, c in zip(raws, counts)]
        mean = np.add.reduceat(probs * weight[:, None], starts, axis=0) / np.add.reduceat(weight, starts)[:, None]
        best = mean.argmax(1)
        for k, b, row in zip(part, best, mean):
            langs[k], scores[k] = net.langs[b], float(min(1.0, row[b]))
    return langs, scores


def held_out() -> F.Column:
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1


def training_windows(docs: DataFrame, rows: int = SAMPLE_ROWS, windows: int = SAMPLE_WINDOWS) -> tuple[list[str], list[str]]:
    """Windows and languages of the bounded sample; whole texts never reach the driver."""
    mix = F.xxhash64("doc_id", F.lit("sample"))
    fair = docs.select("doc_id", "lang").where(F.col("lang").isNotNull() & F.col("doc_id").isNotNull() & ~held_out())
    # first within salts of a language, then among what they keep: no task ranks all rows of a language
    fair = fair.withColumn("mix", mix).withColumn("salt", F.pmod("mix", F.lit(SALTS)))
    for keys in (["lang", "salt"], ["lang"]):
        order = Window.partitionBy(*keys).orderBy("mix", "doc_id")
        fair = fair.withColumn("nth", F.row_number().over(order)).where(F.col("nth") <= rows)
    ids = fair.select("doc_id").distinct()
    n = F.char_length("text")
    start = F.lit(1) + F.pmod(F.xxhash64("doc_id", F.col("w")), F.greatest(n - WINDOW, F.lit(1)))
    cut = (
        docs.select("doc_id", "lang", "text").where(F.col("lang").isNotNull() & F.col("text").isNotNull())
        .join(F.broadcast(ids), "doc_id")  # at most `rows` for each language
        .withColumn("w", F.explode(F.sequence(F.lit(0), F.lit(windows - 1))))
        .select("lang", "doc_id", "w", F.substring(F.col("text"), start.cast("int"), F.lit(WINDOW)).alias("part"))
    )
    found = sorted((r[0], r[1], r[2], r[3]) for r in cut.collect() if _LETTER.search(r[3]))
    return [r[3] for r in found], [r[0] for r in found]


def identify(docs: DataFrame, net: Network | None, keep: list[str] | None = None, names: tuple[str, str] = ("lang_pred", "score")) -> DataFrame:
    """The columns in `keep` (all, if None), the language and its score; columns with these `names` are replaced."""
    fields = [T.StructField(names[0], T.StringType()), T.StructField(names[1], T.DoubleType())]
    return append_columns(docs, "text", fields, lambda: lambda texts: list(predict(net, texts)), keep, "langid")


def train(docs: DataFrame) -> Network | None:
    net = fit(*training_windows(docs))
    give_back()
    return net


def op5_language_id(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return identify(docs, train(docs), ["doc_id"]).select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "lang_pred", "score")
