"""Toxicity by a subsequence string-kernel support vector machine with Nystrom landmarks.

The kernel of two words sums over all triples of letters that both hold in order, within a span of a few places; each
counts decay ** (places spanned) in each word, so gaps and inserted characters weaken a match but do not end it. It is
normalised to 1 for equal words and squared. Characters that no landmark has are gaps; letters set apart by spaces are
read as one word too. Landmarks are training words that stand out in toxic texts. A text's kernel row is the sum over
its words, mapped by the inverse root of the landmarks' own kernel matrix; a linear machine with squared hinge loss
separates log sums, densities and maxima, and a logistic curve fitted on held-out folds turns margins into scores.

The labels are of whole texts, so each labelled text is one training example. Fitting uses at most `most` labelled
texts, those of least hash, whatever the size of the corpus; scoring covers every whole text.

Rows: a null or empty text is scored on zero features; a doc_id labelled more than once counts as toxic if any label
says so; without both classes every score is 0; repeated rows are scored each; other columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import give_back, lean

SPAN, DECAY, FLOOR = 7, 0.6, 0.35
APART = re.compile(r"(?<!\S)(?:\S ){3,}\S(?!\S)")
OFFSETS = [(a, b) for b in range(2, SPAN) for a in range(1, b)]


class SubsequenceKernel:
    """Kernel rows of words against fixed landmarks."""

    def __init__(self, landmarks: list[str]):
        self.landmarks = landmarks
        letters = sorted({c for w in landmarks for c in w if c.isalpha()})
        self.code = np.zeros(0x110000 if any(ord(c) > 0x2FFF for c in letters) else 0x3000, np.int64)
        for i, c in enumerate(letters):
            self.code[ord(c)] = i + 1
        self.size = len(letters) + 1
        self.at = np.full(self.size**3, -1, np.int32)
        weights: dict[int, dict[int, float]] = {}
        for z, word in enumerate(landmarks):
            for triple, w in self.triples(word).items():
                weights.setdefault(triple, {})[z] = w
        self.weight = np.zeros((len(weights), len(landmarks)), np.float32)
        for k, (triple, row) in enumerate(weights.items()):
            self.at[triple] = k
            for z, w in row.items():
                self.weight[k, z] = w
        self.own = np.sqrt((self.weight**2).sum(axis=0))

    def coded(self, text: str) -> np.ndarray:
        points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        return self.code[np.minimum(points, len(self.code) - 1)]

    def triples(self, word: str) -> dict[int, float]:
        c, out = self.coded(word), {}
        for a, b in OFFSETS:
            for i in range(len(c) - b):
                if c[i] and c[i + a] and c[i + b]:
                    key = int((c[i] * self.size + c[i + a]) * self.size + c[i + b])
                    out[key] = out.get(key, 0.0) + DECAY ** (b + 1)
        return out

    def letters(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The codes of all characters of the words, and the number of the word that each is in."""
        joined = "\n".join(words)
        breaks = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32) == 10
        return self.coded(joined), np.concatenate([[0], np.cumsum(breaks)[:-1]]) if len(breaks) else np.zeros(0, np.int64)

    def norms(self, words: list[str]) -> np.ndarray:
        """The roots of the words' kernels with themselves."""
        c, word = self.letters(words)
        keys, weights = [], []
        for a, b in OFFSETS:
            if len(c) > b:
                x, y, z, own = c[: len(c) - b], c[a : len(c) - b + a], c[b:], word[: len(c) - b]
                sound = (x > 0) & (y > 0) & (z > 0) & (own == word[b:])
                keys.append(((own[sound] * self.size + x[sound]) * self.size + y[sound]) * self.size + z[sound])
                weights.append(np.full(sound.sum(), DECAY ** (b + 1)))
        key, weight = np.concatenate(keys), np.concatenate(weights)
        order = np.argsort(key)
        key = key[order]
        begin = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        return np.sqrt(np.bincount(key[begin] // self.size**3, np.add.reduceat(weight[order], begin) ** 2, len(words)))

    def rows(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The numbers of the words that come near a landmark, and their kernel rows."""
        c, word = self.letters(words)
        least, hits = np.zeros(len(words)), []
        for a, b in OFFSETS:
            if len(c) <= b:
                continue
            x, y, z, own = c[: len(c) - b], c[a : len(c) - b + a], c[b:], word[: len(c) - b]
            sound = (x > 0) & (y > 0) & (z > 0) & (own == word[b:])
            own = own[sound]
            least += np.bincount(own, minlength=len(words)) * DECAY ** (2 * b + 2)
            k = self.at[(x[sound] * self.size + y[sound]) * self.size + z[sound]]
            hits.append((own[k >= 0], k[k >= 0], np.full((k >= 0).sum(), DECAY ** (b + 1), np.float32)))
        none = np.zeros(0, np.int64), np.zeros((0, len(self.landmarks)))
        if not hits:
            return none
        at, k, w = (np.concatenate(x) for x in zip(*hits, strict=True))
        if not len(at):
            return none
        # a bound on the kernel first: most words are far from all landmarks
        order = np.argsort(at, kind="stable")
        at, k, w = at[order], k[order], w[order]
        bound = np.bincount(at, weights=w * np.sqrt((self.weight**2 / self.own**2).max(axis=1))[k], minlength=len(words)) / np.sqrt(np.maximum(least, 1e-12))
        keep = bound[at] >= FLOOR
        at, k, w = at[keep], k[keep], w[keep]
        if not len(at):
            return none
        begin = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
        out = np.add.reduceat(self.weight[k] * w[:, None], begin) / self.own
        near = at[begin]
        close = (out.max(axis=1) / np.sqrt(least[near])) >= FLOOR
        near, out = near[close], out[close]
        out = out / self.norms([words[i] for i in near])[:, None] if len(near) else out
        close = out.max(axis=1, initial=0) >= FLOOR
        return near[close], out[close] ** 2


@dataclass
class Model:
    """A fitted machine; features() keeps what it learns about words up to `kept` words."""

    landmarks: list[str]
    root: np.ndarray
    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    slope: float
    shift: float
    kept: int = 400_000
    known: dict[str, int] = field(default_factory=dict)

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("known", "kernel", "table")} | {"known": {}}

    def _ready(self) -> None:
        if not hasattr(self, "kernel") or len(self.known) > self.kept:
            self.kernel, self.known, self.table = getattr(self, "kernel", None) or SubsequenceKernel(self.landmarks), {}, [np.zeros(len(self.landmarks))]

    def features(self, texts: list[str | None]) -> np.ndarray:
        out = np.zeros((len(texts), 3 * len(self.landmarks)))
        m = len(self.landmarks)
        for begin in range(0, len(texts), 64):
            self._ready()
            counts = []
            for text in texts[begin : begin + 64]:
                low = (text or "").lower()
                words = low.split()
                counts.append((Counter(words + [x.replace(" ", "") for x in APART.findall(low)]), len(words)))
            known = self.known
            new = list({w for count, _ in counts for w in count if w not in known})
            known.update(dict.fromkeys(new, 0))
            for at, row in zip(*self.kernel.rows(new), strict=True):
                known[new[at]] = len(self.table)
                self.table.append(row)
            for i, (count, n) in enumerate(counts, begin):
                hits = [(k, c) for w, c in count.items() if (k := known[w])]
                if hits:
                    rows = np.array([self.table[k] for k, _ in hits])
                    total = np.array([c for _, c in hits], float) @ rows
                    out[i, :m] = np.log1p(total) @ self.root
                    out[i, m : 2 * m] = np.sqrt(100 * total / max(n, 20)) @ self.root
                    out[i, 2 * m :] = rows.max(axis=0) @ self.root
        return out

    def forget(self) -> None:
        """Drops what it knows of words; it learns them again where it is used."""
        self.known = {}
        for name in ("kernel", "table"):
            self.__dict__.pop(name, None)

    def margins(self, x: np.ndarray) -> np.ndarray:
        return (x - self.mean) / self.scale @ self.weights[1:] + self.weights[0]

    def scores(self, texts: list[str | None]) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * self.margins(self.features(texts)) + self.shift, -500, 500)))


def pick_landmarks(texts: list[str], toxic: np.ndarray, count: int, family: int = 2) -> list[str]:
    """Words and beginnings of words whose presence tells toxic texts most, by the log-likelihood ratio."""
    seen: tuple[Counter, Counter] = (Counter(), Counter())
    told: set[str] = set()
    for label in (1, 0):
        for text, y in zip(texts, toxic, strict=True):
            if y == label:
                words = {re.sub(r"^\W+|\W+$", "", w) for w in (text or "").lower().split()}
                begins = {w[:n] for w in words for n in range(4, min(len(w), 12) + 1)}
                seen[label].update(begins if label else begins & told)
        if label:
            told = {w for w, n in seen[1].items() if n >= 3}
    n0, n1 = (toxic == 0).sum(), (toxic == 1).sum()

    def ratio(word: str) -> float:
        a, b = seen[1][word], seen[0][word]
        if a < 3 or a / n1 <= 2 * b / n0:
            return 0.0
        share = (a + b) / (n0 + n1)
        term = lambda k, n: (k * math.log(k / n / share) if k else 0.0) + ((n - k) * math.log((n - k) / n / (1 - share)) if k < n else 0.0)
        return term(a, n1) + term(b, n0)

    ranked = [w for r, w in sorted((-ratio(w), w) for w in told if sum(c.isalpha() for c in w) > 3) if r < -6]
    chosen: list[str] = []
    for word in ranked:  # no family of words takes all places
        if len(chosen) < count and sum(word[:4] == c[:4] for c in chosen) < family:
            chosen.append(word)
    return chosen


def fit_machine(x: np.ndarray, y: np.ndarray, penalty: float, rounds: int = 30) -> np.ndarray:
    """Weights, the intercept first, of a linear machine with squared hinge loss, by Newton steps."""
    x, sign = np.column_stack([np.ones(len(x)), x]), np.where(y > 0, 1.0, -1.0)
    balance = np.where(y > 0, (y == 0).sum() / max(1, (y > 0).sum()), 1.0) ** 0.5
    ridge = penalty * np.eye(x.shape[1])
    ridge[0, 0] = 1e-6
    w = np.zeros(x.shape[1])
    for _ in range(rounds):
        inside = sign * (x @ w) < 1
        xs = x[inside] * balance[inside, None]
        new = np.linalg.solve(ridge + xs.T @ x[inside], xs.T @ sign[inside])
        if np.allclose(new, w, atol=1e-8):
            break
        w = (w + new) / 2 if _ > 10 else new
    return w


def fit_curve(margin: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and shift of the logistic curve that gives the chance of label 1."""
    a, b = 1.0, 0.0
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(a * margin + b, -30, 30)))
        g = np.array([((p - y) * margin).sum() + 1e-3 * a, (p - y).sum()])
        r = p * (1 - p)
        h = np.array([[(r * margin**2).sum() + 1e-3, (r * margin).sum()], [(r * margin).sum(), r.sum() + 1e-9]])
        step = np.linalg.solve(h, g)
        a, b = a - step[0], b - step[1]
        if abs(step).max() < 1e-9:
            break
    return float(a), float(b)


def train(texts: list[str], toxic: np.ndarray, landmarks: int = 48, penalty: float = 30.0, folds: int = 4) -> Model | None:
    if not len(toxic) or toxic.min() == toxic.max():
        return None
    words = pick_landmarks(texts, toxic, landmarks)
    if not words:
        return None
    kernel = SubsequenceKernel(words)
    own = np.zeros((len(words), len(words)))
    at, rows = kernel.rows(words)
    own[at] = rows
    own = (own + own.T) / 2
    value, vector = np.linalg.eigh(own)
    root = vector @ np.diag(1 / np.sqrt(np.maximum(value, 0.05))) @ vector.T
    model = Model(words, root, np.zeros(3 * len(words)), np.ones(3 * len(words)), np.zeros(3 * len(words) + 1), 1.0, 0.0)
    x = model.features(texts)
    model.mean, model.scale = x.mean(axis=0), x.std(axis=0) + 1e-3
    z = (x - model.mean) / model.scale
    margin, fold = np.zeros(len(z)), np.arange(len(z)) % folds
    for f in range(folds):
        w = fit_machine(z[fold != f], toxic[fold != f], penalty)
        margin[fold == f] = z[fold == f] @ w[1:] + w[0]
    model.weights = fit_machine(z, toxic, penalty)
    model.slope, model.shift = fit_curve(margin, toxic)
    model.forget()
    return model


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, most: int = 6000) -> Model | None:
    """Fits on the labelled documents that aren't held out; the `most` of least hash where there are more."""
    known = labels.filter("doc_id is not null and toxic is not null").filter(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    known = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    rows: pd.DataFrame = docs.select("doc_id", "text").join(F.broadcast(known), "doc_id").toPandas()  # bounded by most
    rows = rows.sort_values(["doc_id", "text"]).drop_duplicates("doc_id")
    order = rows["doc_id"].map(lambda i: hash((int(i) * 2654435761) & 0xFFFFFFFF)).to_numpy().argsort(kind="stable")
    texts, toxic = rows["text"].iloc[order].tolist(), rows["toxic"].iloc[order].to_numpy()
    del rows, order
    model = train(texts, toxic)
    del texts
    give_back()  # the driver needs it for the stages that follow
    return model


SCHEMA = "doc_id long, held_out boolean, score double, predicted int"


def scored(docs: DataFrame, model: Model | None) -> DataFrame:
    """docs with the column score, in place of one of that name."""
    docs = docs.drop("score")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column("text").to_pylist()
            score = model.scores(texts) if model else np.zeros(len(texts))
            yield batch.append_column("score", pa.array(score, pa.float64()))

    return docs.mapInArrow(lean(run), T.StructType([*docs.schema.fields, T.StructField("score", T.DoubleType())]))


def judge(docs: DataFrame, labels: DataFrame, limit: float = 0.3, most: int = 6000) -> DataFrame:
    """doc_id, held_out, score and predicted of every row of docs (doc_id, text); labels: doc_id, toxic."""
    df = scored(docs.select("doc_id", "text"), fit(docs, labels, most))
    return df.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= limit).cast("int").alias("predicted"))
