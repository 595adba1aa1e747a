"""Document quality by attention-based multiple-instance learning.

A document is a bag of passages of ``PASSAGE`` words. A passage is encoded as the mean of its words'
learnt embeddings (words share ``BUCKETS`` rows by a hash) together with style features, through one
hidden layer; gated attention (tanh times sigmoid) weighs the passages; the weighted representation
gives the score. Embeddings, attention and scorer are learnt together from document labels alone, so
the attention learns which passages matter.

Learning takes a bounded sample of labelled documents (about ``max_documents``, chosen by a hash of
the key), encoded on the executors; scoring reads whole texts.

Defined results: null text counts as empty, an empty text is one passage of zeros; of rows that repeat
a labelled key the least text is learnt from, and the highest label; without both labels in the sample
the score is the share of label 1, or 0.5; an empty table gives an empty result; the output holds key,
score and decision only.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coarsesample.llm import worker

PASSAGE = 64
_LETTERS = re.compile(r"[^\W\d_]")
_SYMBOLS = re.compile(r"[^\w\s.,;:'\"()?-]")
_RUN = re.compile(r"(.)\1")
WORD_FEATURES = ("length", "long", "upper", "title", "digits", "symbols", "doubled_symbol", "no_letter", "ends_sentence", "ends_comma", "url_or_mail")
BAG_FEATURES = ("distinct", "repeats", "run", "words")
N_STYLE = len(WORD_FEATURES) + len(BAG_FEATURES)
BUCKETS = 256
N_FEATURES = N_STYLE + BUCKETS


def word_features(word: str) -> list[float]:
    """Style of one word."""
    n = max(1, len(word))
    has = len(_LETTERS.findall(word))
    symbols = _SYMBOLS.findall(word)
    return [
        min(n, 40) / 10.0,
        float(n > 25),
        float(has > 1 and word.isupper()),
        float(word[:1].isupper()),
        sum(map(str.isdigit, word)) / n,
        len(symbols) / n,
        float(bool(symbols) and bool(_RUN.search("".join(symbols)))),
        float(not has),
        float(word[-1:] in ".!?"),
        float(word[-1:] == ","),
        float("@" in word or "://" in word),
    ]


class _Words(dict):
    """Word to its row in a growing feature table; emptied when full."""

    def __init__(self, limit: int = 200_000):
        super().__init__()
        self.limit = limit
        self.table = np.zeros((limit + 4096, len(WORD_FEATURES)), np.float32)
        self.bucket = np.zeros(limit + 4096, np.int64)

    def __missing__(self, word: str) -> int:
        at = len(self)
        if at >= len(self.table):
            self.table = np.concatenate([self.table, np.zeros_like(self.table)])
            self.bucket = np.concatenate([self.bucket, np.zeros_like(self.bucket)])
        self.table[at] = word_features(word)
        self.bucket[at] = xxhash.xxh3_64_intdigest(word.lower().encode("utf-8", "surrogatepass")) % BUCKETS
        self[word] = at
        return at

    def trim(self) -> None:
        if len(self) > self.limit:
            self.clear()


_words: list[_Words] = []


def encode(text: str | None) -> np.ndarray:
    """Passages by features: style, then the share of the passage's words in each bucket."""
    worker.claim("quality", _words.clear)
    if not _words:
        _words.append(_Words())
    known = _words[0]
    known.trim()
    words = (text or "").split()
    if not words:
        return np.zeros((1, N_FEATURES), np.float32)
    ids = np.fromiter(map(known.__getitem__, words), np.int64, len(words))
    starts = np.arange(0, len(ids), PASSAGE)
    if len(starts) > 1 and len(ids) - starts[-1] < PASSAGE // 4:
        starts = starts[:-1]
    sizes = np.diff(np.append(starts, len(ids))).astype(np.float32)
    out = np.empty((len(starts), N_FEATURES), np.float32)
    k = len(WORD_FEATURES)
    out[:, :k] = np.add.reduceat(known.table[ids], starts, axis=0) / sizes[:, None]
    passage = np.repeat(np.arange(len(starts)), sizes.astype(np.int64))
    seen = np.unique(passage * (len(known) + 1) + ids) // (len(known) + 1)
    out[:, k] = np.bincount(seen, minlength=len(starts)) / sizes
    again = np.zeros(len(ids), np.float32)
    again[1:] = ids[1:] == ids[:-1]
    again[starts] = 0
    out[:, k + 1] = np.add.reduceat(again, starts) / sizes
    twice = np.zeros(len(ids), np.float32)
    twice[2:] = again[2:] * again[1:-1]
    out[:, k + 2] = np.add.reduceat(twice, starts) / sizes
    out[:, k + 3] = np.minimum(sizes, PASSAGE) / PASSAGE
    lexical = np.bincount(passage * BUCKETS + known.bucket[ids], minlength=len(starts) * BUCKETS).reshape(-1, BUCKETS)
    out[:, N_STYLE:] = lexical / sizes[:, None]
    return out


class AttentionModel:
    """Passage encoder, gated attention and scorer, trained together with Adam on whole bags.

    ``attention=False`` gives all passages the same weight: mean pooling, to compare with.
    """

    def __init__(self, hidden: int = 16, gate: int = 8, seed: int = 7, attention: bool = True):
        rng = np.random.default_rng(seed)
        self.attention = attention
        put = lambda *shape: rng.normal(0, 1 / np.sqrt(shape[0]), shape).astype(np.float32)
        self.p = {"E": put(N_FEATURES, hidden), "e": np.zeros(hidden, np.float32), "V": put(hidden, gate), "U": put(hidden, gate), "w": put(gate), "c": put(hidden), "b": np.zeros(1, np.float32)}
        self.mean, self.scale = np.zeros(N_FEATURES), np.ones(N_FEATURES)
        self.constant: float | None = None

    def scaled(self, x: np.ndarray) -> np.ndarray:
        """Features in units of their spread; a passage holds few of the buckets, so together they weigh about as much as the style."""
        out = np.clip((x - self.mean) / self.scale, -8, 8)
        out[:, N_STYLE:] /= 16
        return out

    def forward(self, x: np.ndarray, starts: np.ndarray) -> dict:
        """All layers over the scaled passages of bags that begin at ``starts``."""
        p, f = self.p, {}
        sizes = np.diff(np.append(starts, len(x)))
        f["bag"] = np.repeat(np.arange(len(starts)), sizes)
        f["x"] = x
        f["h"] = np.tanh(f["x"] @ p["E"] + p["e"])
        f["t"], f["s"] = np.tanh(f["h"] @ p["V"]), 1 / (1 + np.exp(-f["h"] @ p["U"]))
        a = (f["t"] * f["s"]) @ p["w"] * float(self.attention)
        a = np.exp(a - np.maximum.reduceat(a, starts)[f["bag"]])
        f["a"] = a / np.add.reduceat(a, starts)[f["bag"]]
        f["z"] = np.add.reduceat(f["h"] * f["a"][:, None], starts, axis=0)
        f["y"] = 1 / (1 + np.exp(-np.clip(f["z"] @ p["c"] + p["b"], -30, 30)))
        return f

    def gradients(self, f: dict, starts: np.ndarray, y: np.ndarray, decay: float) -> dict:
        p, bag = self.p, f["bag"]
        d = (f["y"] - y) / len(y)
        dz = d[:, None] * p["c"]
        da = np.sum(f["h"] * dz[bag], axis=1)
        dl = f["a"] * (da - np.add.reduceat(f["a"] * da, starts)[bag])
        dl = dl * float(self.attention)
        dg = dl[:, None] * p["w"]
        dt, ds = dg * f["s"] * (1 - f["t"] ** 2), dg * f["t"] * f["s"] * (1 - f["s"])
        dh = f["a"][:, None] * dz[bag] + dt @ p["V"].T + ds @ p["U"].T
        dx = dh * (1 - f["h"] ** 2)
        g = {"E": f["x"].T @ dx, "e": dx.sum(0), "V": f["h"].T @ dt, "U": f["h"].T @ ds, "w": (f["t"] * f["s"]).T @ dl, "c": f["z"].T @ d, "b": np.array([d.sum()])}
        return {k: v + decay * p[k] for k, v in g.items()}

    def fit(self, bags: list[np.ndarray], labels: np.ndarray, steps: int = 150, rate: float = 0.02, decay: float = 3e-4) -> AttentionModel:
        labels = np.asarray(labels, np.float32)
        if not len(labels) or labels.min() == labels.max():
            self.constant = float(labels.mean()) if len(labels) else 0.5
            return self
        x = np.concatenate(bags).astype(np.float32)
        starts = np.concatenate([[0], np.cumsum([len(b) for b in bags])[:-1]])
        self.mean, self.scale = x.mean(0, dtype=float).astype(np.float32), x.std(0, dtype=float).astype(np.float32) + np.float32(1e-3)
        x = self.scaled(x).astype(np.float32)
        m, v = ({k: np.zeros_like(w) for k, w in self.p.items()} for _ in range(2))
        for step in range(1, steps + 1):
            g = self.gradients(self.forward(x, starts), starts, labels, decay)
            for k in self.p:
                m[k] = 0.9 * m[k] + 0.1 * g[k]
                v[k] = 0.999 * v[k] + 0.001 * g[k] ** 2
                self.p[k] = self.p[k] - rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
        return self

    def scores(self, bags: list[np.ndarray]) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(bags), self.constant)
        if not bags:
            return np.zeros(0)
        starts = np.concatenate([[0], np.cumsum([len(b) for b in bags])[:-1]]).astype(np.int64)
        return self.forward(self.scaled(np.concatenate(bags).astype(float)), starts)["y"]


def train(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "quality", max_documents: int = 2000) -> AttentionModel:
    """Fit on a hash-chosen sample of at most about ``max_documents`` labelled documents.

    The sample's keys are broadcast (bounded by that number); their texts are encoded where they
    lie and only the passages' features reach the driver.
    """
    known = labels.where(F.col(label).isNotNull() & F.col(key).isNotNull()).select(F.col(key).cast("string").alias("k"), F.col(label).cast("int").alias("y"))
    n = known.agg(F.approx_count_distinct("k", 0.02)).first()[0]
    at = F.pmod(F.xxhash64("k", F.lit("sample")), F.lit(1 << 62))
    chosen = known.where(at < F.lit(int(min(1.0, max_documents / max(1, n)) * (1 << 62)))).groupBy("k").agg(F.max("y").alias("y"))
    held = docs.select(F.col(key).cast("string").alias("k"), F.coalesce(F.col(text), F.lit("")).alias("text")).join(F.broadcast(chosen), "k")
    bags = held.groupBy("k", "y").agg(F.min("text").alias("text"))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            coded = [encode(t).astype(np.float16) for t in batch["text"]]
            yield pd.DataFrame({"k": batch["k"], "y": batch["y"], "n": [len(c) for c in coded], "bag": [c.tobytes() for c in coded]})

    rows = bags.mapInPandas(run, "k string, y int, n int, bag binary").collect()
    rows.sort(key=lambda r: r["k"])
    return AttentionModel().fit([np.frombuffer(r["bag"], np.float16).reshape(r["n"], N_FEATURES) for r in rows], np.array([r["y"] for r in rows]))


def score(docs: DataFrame, model: AttentionModel, threshold: float = 0.7, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, score, predicted for every document."""
    kind = docs.schema[key].dataType
    given = docs.select(F.col(key).cast("string").alias(key), F.col(text).alias("text"))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for i in range(0, len(batch), 500):
                part = batch.iloc[i : i + 500]
                found = model.scores([encode(t) for t in part["text"]])
                yield pd.DataFrame({key: part[key], "score": found, "predicted": (found >= threshold).astype(np.int32)})

    return given.mapInPandas(run, f"`{key}` string, score double, predicted int").withColumn(key, F.col(key).cast(kind))


def accepts(model: AttentionModel, threshold: float = 0.7):
    """A column function of the text: whether its score reaches the threshold. Never null."""

    @F.pandas_udf("boolean")
    def good(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for texts in batches:
            parts = [texts.iloc[i : i + 500] for i in range(0, len(texts), 500)]
            yield pd.Series(np.concatenate([model.scores([encode(t) for t in p]) >= threshold for p in parts]) if parts else np.zeros(0, bool))

    return good
