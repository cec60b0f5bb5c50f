"""Quality classifier from positive and unlabelled text.

Trusted positives and unlabelled web text train a small network by the non-negative unbiased risk: with class prior p,
risk = p E_pos[loss(f)] + max(0, E_unl[loss(-f)] - p E_pos[loss(-f)]); where the second part falls below zero its own
gradient is undone instead. The prior is estimated from a first classifier of positives against unlabelled text: the
smallest ratio, over score thresholds, of the shares of both that lie above it. No negative label is read.

Features are shapes of the text alone (shares of characters, repetition, lengths of words and lines).
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import map_rows, whole_text

#: Bound of the sample of each kind (positives, unlabelled) that the network is fitted on.
SAMPLE = 12_000
THRESHOLD = 0.7
MARKS = b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"


def features(text: str) -> np.ndarray:
    """Fixed-length description of a text; empty ones give zeros."""
    raw = text.encode()
    words, lines = text.split(), [x for x in text.split("\n") if x.strip()]
    n, size = max(1, len(words)), max(1, len(raw))
    count = np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
    distinct = len(set(words))
    pairs = len(set(zip(words, words[1:])))
    same = sum(map(str.__eq__, words, words[1:]))
    marked = sum(not x[-1].isalnum() for x in words)
    doubly = sum(len(x) > 1 and not x[-1].isalnum() and not x[-2].isalnum() for x in words)
    bare = sum(not x[0].isalnum() for x in words)
    upper = sum(map(str.isupper, words))
    lengths = np.fromiter(map(len, words), np.float64, len(words)) if words else np.zeros(1)
    shares = [
        distinct / n, pairs / n, same / n, marked / n, doubly / n, bare / n, upper / n, len(set(lines)) / max(1, len(lines)),
        count[48:58].sum() / size, count[65:91].sum() / size, count[97:123].sum() / size, count[128:].sum() / size,
        (count[32] + count[9]) / size, (count[10] + count[13]) / size, count[:9].sum() / size, *count[list(MARKS)] / size,
    ]
    logs = [np.log1p(len(words)), np.log1p(len(raw)), np.log1p(len(lines)), np.log1p(distinct) - np.log1p(n), lengths.mean() / 10, lengths.std() / 10, np.log1p(lengths.max())]
    return np.array([*np.sqrt(np.maximum(0, shares)), *logs], np.float32)


N_FEATURES = len(features("a b"))


@dataclass(frozen=True)
class Network:
    """One hidden layer over scaled features; `prior` answers where there was nothing to learn from."""

    mean: np.ndarray
    scale: np.ndarray
    layers: tuple[np.ndarray, ...]
    prior: float

    def logits(self, x: np.ndarray) -> np.ndarray:
        w1, b1, w2, b2 = self.layers
        return np.tanh(np.clip((x - self.mean) / self.scale, -6, 6) @ w1 + b1) @ w2 + b2

    def scores(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logits(x), -30, 30)))


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def risk(layers: list[np.ndarray], xp: np.ndarray, xu: np.ndarray, prior: float | None) -> tuple[float, list[np.ndarray]]:
    """A batch's risk under the logistic loss, and the gradient to step by.

    With a prior: that of positives, times the prior, and the negatives' part, which is what unlabelled texts cost as
    negatives less what the positives among them do. Where that part falls below zero the risk counts it as zero, and the
    step undoes it: its gradient with the sign turned. Without a prior: positives against unlabelled.
    """
    x = np.concatenate([xp, xu])
    h = np.tanh(x @ layers[0] + layers[1])
    z = h @ layers[2] + layers[3]
    zp, zu = z[: len(xp)], z[len(xp) :]
    if prior is None:
        value = np.logaddexp(0, -zp).mean() + np.logaddexp(0, zu).mean()
        g = np.concatenate([(_sigmoid(zp) - 1) / len(xp), _sigmoid(zu) / len(xu)])
    else:
        rest = np.logaddexp(0, zu).mean() - prior * np.logaddexp(0, zp).mean()
        value = prior * np.logaddexp(0, -zp).mean() + max(0.0, rest)
        g_rest = np.concatenate([-prior * _sigmoid(zp) / len(xp), _sigmoid(zu) / len(xu)])
        g_pos = np.concatenate([prior * (_sigmoid(zp) - 1) / len(xp), np.zeros(len(xu))])
        g = g_pos + g_rest if rest >= 0 else -g_rest
    gh = np.outer(g, layers[2]) * (1 - h * h)
    return float(value), [x.T @ gh, gh.sum(0), h.T @ g, np.array([g.sum()])]


def _train(pos: np.ndarray, unl: np.ndarray, prior: float | None, seed: int, epochs: int = 40, hidden: int = 24, rate: float = 0.01, decay: float = 1e-4) -> tuple:
    """Adam on the logistic loss; with a prior the non-negative risk, without one plain positives against unlabelled."""
    rng = np.random.default_rng(seed)
    d = pos.shape[1]
    layers = [rng.normal(0, 1 / np.sqrt(d), (d, hidden)), np.zeros(hidden), rng.normal(0, 1 / np.sqrt(hidden), hidden), np.zeros(1)]
    moments = [(np.zeros_like(x), np.zeros_like(x)) for x in layers]
    half = max(1, min(256, len(pos), len(unl)))
    steps, total = max(1, max(len(pos), len(unl)) // half), 0
    for epoch in range(epochs):
        p, u = rng.permutation(len(pos)), rng.permutation(len(unl))
        for s in range(steps):
            xp, xu = pos[np.take(p, range(s * half, (s + 1) * half), mode="wrap")], unl[np.take(u, range(s * half, (s + 1) * half), mode="wrap")]
            _, grads = risk(layers, xp, xu, prior)
            total += 1
            step = rate * (1 - epoch / epochs)
            for k, grad in enumerate(grads):
                m, v = moments[k]
                grad = grad + decay * layers[k]
                m[...] = 0.9 * m + 0.1 * grad
                v[...] = 0.999 * v + 0.001 * grad * grad
                layers[k] = layers[k] - step * (m / (1 - 0.9**total)) / (np.sqrt(v / (1 - 0.999**total)) + 1e-8)
    return tuple(layers)


def estimate_prior(pos_scores: np.ndarray, unl_scores: np.ndarray, delta: float = 0.1) -> float:
    """The least ratio of unlabelled to positive shares above a threshold, with the deviation both may have added."""
    slack = np.sqrt(np.log(4 / delta) / 2)
    n, m = len(pos_scores), len(unl_scores)
    p, u = np.sort(pos_scores), np.sort(unl_scores)
    cuts = np.quantile(pos_scores, np.linspace(0, 0.9, 91))
    above_p, above_u = 1 - np.searchsorted(p, cuts) / n, 1 - np.searchsorted(u, cuts) / m
    bound = above_u / above_p + (slack / np.sqrt(m) + slack / np.sqrt(n)) / above_p
    best = int(np.argmin(bound))
    return float(np.clip(above_u[best] / above_p[best], 0.02, 0.98))


def fit_network(pos: np.ndarray, unl: np.ndarray, seed: int = 7) -> Network:
    if len(pos) < 2 or len(unl) < 2:
        d = N_FEATURES
        return Network(np.zeros(d), np.ones(d), (np.zeros((d, 1)), np.zeros(1), np.zeros(1), np.zeros(1)), 0.5)
    every = np.concatenate([pos, unl]).astype(np.float64)
    mean, scale = every.mean(0), every.std(0) + 1e-3
    p, u = (np.clip((x - mean) / scale, -6, 6) for x in (pos, unl))
    fold_p, fold_u = np.arange(len(p)) % 3 == 0, np.arange(len(u)) % 3 == 0
    first = Network(np.zeros(p.shape[1]), np.ones(p.shape[1]), _train(p[~fold_p], u[~fold_u], None, seed, epochs=12), 0.5)
    prior = estimate_prior(first.logits(p[fold_p]), first.logits(u[fold_u]))
    return Network(mean, scale, _train(p, u, prior, seed), prior)


def held_out(doc_id: Column) -> Column:
    """Rows whose labels must not be learnt from. A null id has no label to learn."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def _draw(n: int) -> Column:
    return F.pmod(F.xxhash64("doc_id", F.lit("draw")), F.lit(1 << 30)) < int(min(1.0, SAMPLE / max(1, n)) * (1 << 30))


def fit(docs: DataFrame, labels: DataFrame) -> Network:
    """Fits on at most about SAMPLE trusted positives and SAMPLE texts without regard to their labels, drawn by a hash of
    the id. Rows that are held out by id give neither labels nor text, and rows with a null id no text. Null and empty texts
    are texts like others; a repeated row counts as often as it is drawn. Without positives or texts the network scores all
    texts alike. Other columns are left out."""
    usable = ~held_out(F.col("doc_id")) & F.col("doc_id").isNotNull()
    trusted = labels.where(usable & (F.col("quality") == 1)).select("doc_id").distinct()
    trusted = trusted.where(_draw(trusted.count())).withColumn("_trusted", F.lit(True))
    texts = whole_text(docs).where(usable)
    # bounded: about SAMPLE ids
    picked = texts.withColumn("_any", _draw(docs.where(usable).count())).join(F.broadcast(trusted), "doc_id", "left")
    picked = picked.where("_any OR _trusted").selectExpr("doc_id", "text", "coalesce(_trusted, false) AS trusted", "_any AS other")

    def make():
        return lambda c: {"trusted": c["trusted"], "other": c["other"], "x": [features(x).tolist() for x in c["text"]]}

    rows = map_rows(picked, make, "trusted boolean, other boolean, x array<float>").collect()
    table = lambda kept: np.array([r.x for r in kept], np.float64).reshape(-1, N_FEATURES)
    rows.sort(key=lambda r: tuple(r.x))
    order = np.random.default_rng(3).permutation(len(rows))
    rows = [rows[i] for i in order]
    return fit_network(table([r for r in rows if r.trusted]), table([r for r in rows if r.other]))


def score(docs: DataFrame, network: Network, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, held_out, score, predicted of every whole text. Null texts are empty; repeated rows and null ids stay (a null id
    is not held out); equal texts have equal scores; other columns are left out. An empty table gives an empty one."""

    def make():
        return lambda c: {"doc_id": c["doc_id"], "held_out": c["held_out"], "score": network.scores(np.stack([features(x) for x in c["text"]])).tolist() if c["text"] else []}

    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), held_out(F.col("doc_id")).alias("held_out"))
    scored = map_rows(rows, make, "doc_id bigint, held_out boolean, score double")
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def keep_good(docs: DataFrame, network: Network, threshold: float = 0.5) -> DataFrame:
    """The rows of docs, all their columns, whose text the network accepts. Rows with a null or empty text
    stay: there is nothing to reject. Null ids, repeated rows and columns of any name stay as they are."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                texts = part.column(part.schema.get_field_index("text")).to_pylist()
                good = network.scores(np.stack([features(x or "") for x in texts])) >= threshold
                yield part.filter(pa.array([bool(g) or not x for g, x in zip(good, texts, strict=True)]))

    return docs.mapInArrow(run, docs.schema)
