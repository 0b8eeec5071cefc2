"""Toxic spans by a linear-chain conditional random field.

Texts are chains of words, one chain a sentence (a sentence of more than
``CHAIN`` words is cut into several).  Two states, clean and toxic; emission
weights of hashed features (the word and its leading bytes), transition and
start weights.  Forward-backward marginals are summed up to a document's score
by a small logistic layer, and mark the offending byte offsets.

Labels mark documents, so token labels for training are derived first: features
are picked greedily that occur in toxic sample documents not yet explained and
(almost) never in clean ones; tokens that have one are toxic.  The field then
learns weights for all features and the transitions from these tokens.

The model is fitted on a bounded sample: at most ``per_class`` toxic and
``CLEAN`` times as many clean labelled rows with texts of at most ``max_chars``
characters, taken by a hash of the id.  Of their chains all that hold a toxic
token and every ``clean_share``-th other one train the field; the layer is
trained on all.  The model is a table of 2**BITS numbers whatever the corpus.
Every text is then scored whole, in one scan without a shuffle.

Defined cases: null, empty and wordless texts score as a text without toxic
tokens; repeated rows get equal scores; label rows that are null in any field or
have no document are no training rows; a doc_id labelled both ways is toxic;
where the sample lacks toxic texts, clean texts or any words, nothing can be
learnt and all scores are 0; extra columns are ignored; an empty table gives an
empty result.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import bounded
from .textkernel import NON_ALNUM, U, chunks, words

BITS = 18
CHAIN = 48
PREFIXES = (4, 5, 6)
CLEAN = 4  #: clean sample texts for each toxic one
_STOP = np.zeros(256, bool)
_STOP[[10, 33, 46, 63]] = True


def features(data: np.ndarray, off: np.ndarray):
    """(words, feature numbers of each word, chain number of each word)."""
    w, pre = words(data, off, NON_ALNUM, PREFIXES)
    size = w.end - w.start
    feats = [(w.hash >> U(64 - BITS)).astype(np.int32)]
    for k, h in zip(PREFIXES, pre):
        # a word of no more bytes repeats its own feature: no new information
        feats.append(np.where(size > k, (h >> U(64 - BITS)).astype(np.int32), feats[0]))
    stops = np.zeros(len(data) + 1, np.int32)
    np.cumsum(_STOP[data], out=stops[1:])
    m = len(w.start)
    new = np.ones(m, bool)
    if m:
        new[1:] = (w.text[1:] != w.text[:-1]) | (stops[w.start[1:]] > stops[w.end[:-1]])
        first = np.flatnonzero(new)
        new = (np.arange(m) - first[np.cumsum(new) - 1]) % CHAIN == 0
    return w, np.stack(feats, 1) if m else np.zeros((0, 1 + len(PREFIXES)), np.int32), np.cumsum(new) - 1


@dataclass
class Model:
    weight: np.ndarray = field(default_factory=lambda: np.zeros(1 << BITS, np.float32))
    step: np.ndarray = field(default_factory=lambda: np.zeros((2, 2)))  #: transition weights
    start: np.ndarray = field(default_factory=lambda: np.zeros(2))
    layer: np.ndarray | None = None  #: logistic layer over the marginals

    def emission(self, feats: np.ndarray) -> np.ndarray:
        out = self.weight[feats[:, 0]].astype(np.float64)
        for j in range(1, feats.shape[1]):
            out += np.where(feats[:, j] != feats[:, 0], self.weight[feats[:, j]], 0)
        return out

    def marginals(self, emission: np.ndarray, chain: np.ndarray, pairs: bool = False):
        """Of each word, the probability of the toxic state; with ``pairs``
        also the expected transitions and starts."""
        n = int(chain[-1]) + 1 if len(chain) else 0
        first = np.searchsorted(chain, np.arange(n))
        at = np.arange(len(chain)) - first[chain]
        size = np.bincount(chain, minlength=n)
        order = np.argsort(-size, kind="stable")  # long chains first: live ones are a prefix
        rank = np.empty(n, np.int64)
        rank[order] = np.arange(n)
        width = int(size.max(initial=0))
        e = np.zeros((width, n))
        e[at, rank[chain]] = emission
        live = np.searchsorted(-size[order], -np.arange(width), "left")  # chains longer than t
        step = np.exp(self.step)
        ex = np.exp(np.clip(e, -30, 30))
        a = np.zeros((width, 2, n))
        for t in range(width):
            k = live[t]
            if t == 0:
                x0, x1 = np.full(k, np.exp(self.start[0])), np.exp(self.start[1]) * ex[0, :k]
            else:
                p0, p1 = a[t - 1, 0, :k], a[t - 1, 1, :k]
                x0, x1 = p0 * step[0, 0] + p1 * step[1, 0], (p0 * step[0, 1] + p1 * step[1, 1]) * ex[t, :k]
            z = x0 + x1
            a[t, 0, :k], a[t, 1, :k] = x0 / z, x1 / z
        b = np.ones((width, 2, n))
        two, starts = np.zeros((2, 2)), np.zeros(2)
        for t in range(width - 2, -1, -1):
            k = live[t + 1]
            n0, n1 = b[t + 1, 0, :k], b[t + 1, 1, :k] * ex[t + 1, :k]
            y0, y1 = step[0, 0] * n0 + step[0, 1] * n1, step[1, 0] * n0 + step[1, 1] * n1
            if pairs:
                joint = np.array([[a[t, 0, :k] * step[0, 0] * n0, a[t, 0, :k] * step[0, 1] * n1], [a[t, 1, :k] * step[1, 0] * n0, a[t, 1, :k] * step[1, 1] * n1]])
                two += (joint / joint.sum((0, 1))).sum(2)
            z = y0 + y1
            b[t, 0, :k], b[t, 1, :k] = y0 / z, y1 / z
        both = a * b
        p = (both[:, 1] / np.maximum(both.sum(1), 1e-300))[at, rank[chain]]
        if pairs:
            starts[1] = p[first].sum()
            starts[0] = n - starts[1]
            return p, two, starts
        return p

    def summary(self, p: np.ndarray, text: np.ndarray, texts: int) -> np.ndarray:
        """Per text: largest marginal, log of one plus their sum, one."""
        top = np.zeros(texts)
        np.maximum.at(top, text, p)
        total = np.bincount(text, p, minlength=texts)
        return np.stack([top, np.log1p(np.where(total > 0.02, total, 0)), np.ones(texts)], 1)

    def score(self, summary: np.ndarray) -> np.ndarray:
        if self.layer is None:
            return np.zeros(len(summary))
        return 1 / (1 + np.exp(-np.clip(summary @ self.layer, -40, 40)))


def _counts(texts: list[str | None], toxic: np.ndarray):
    """(toxic texts, clean texts) that have each feature, and the (text,
    feature) pairs of the toxic ones; a few texts at a time."""
    bad, good, pairs = np.zeros(1 << BITS, np.int64), np.zeros(1 << BITS, np.int64), []
    for row, end, data, off in chunks(pa.array(texts, pa.string())):
        w, feats, _ = features(data, off)
        pair = np.unique(((w.text.astype(np.int64)[:, None] << BITS) | feats).ravel())
        doc, feat = (pair >> BITS) + row, pair & ((1 << BITS) - 1)
        hit = toxic[doc]
        bad += np.bincount(feat[hit], minlength=1 << BITS)
        good += np.bincount(feat[~hit], minlength=1 << BITS)
        pairs.append(np.stack([doc[hit], feat[hit]]))
    return bad, good, np.concatenate(pairs, 1)


def _pick(texts: list[str | None], toxic: np.ndarray, precision: float = 0.98) -> np.ndarray:
    """Features that explain the toxic texts, picked greedily."""
    bad, good, (doc, feat) = _counts(texts, toxic)
    able = (bad >= max(3, 0.01 * toxic.sum())) & (bad >= precision * (bad + good))
    doc, feat = doc[able[feat]], feat[able[feat]]
    picked, gains = [], []
    left = toxic.copy()
    while len(feat):
        gain = np.bincount(feat, minlength=1 << BITS)
        best = int(gain.argmax())
        if gain[best] < 2:
            break
        picked.append(best)
        gains.append(bad[best])
        left[doc[feat == best]] = False
        stay = left[doc]
        doc, feat = doc[stay], feat[stay]
    if not picked:
        return np.zeros(0, np.int64)
    # peers of the picked ones that other words of the same texts stood in for
    return np.union1d(picked, np.flatnonzero(able & (bad >= max(5, 0.5 * np.median(gains[: max(1, len(gains) // 2)])))))


def fit(texts: list[str | None], toxic: np.ndarray, rounds: int = 40, clean_share: int = 16) -> Model:
    """Model of texts and their flags; deterministic.  ``clean_share``: of the
    chains of a block without a toxic token, the field learns from every so
    manyth."""
    model = Model()
    if not len(texts) or not toxic.any() or toxic.all():
        return model
    chosen = np.zeros(1 << BITS, bool)
    chosen[_pick(texts, toxic)] = True
    fs, ys, cs, base = [], [], [], 0
    for row, _, data, off in chunks(pa.array(texts, pa.string())):
        w, feats, chain = features(data, off)
        if not len(chain):
            continue
        label = chosen[feats].any(1) & toxic[w.text + row]
        hot = np.zeros(int(chain[-1]) + 1, bool)  # chains with a toxic word, and a share of the others
        hot[chain[label]] = True
        hot[::clean_share] = True
        use = hot[chain]
        fs.append(feats[use])
        ys.append(label[use])
        cs.append(np.unique(chain[use], return_inverse=True)[1] + base)
        base = int(cs[-1][-1]) + 1
    if not base:
        return model
    f, y, c = np.concatenate(fs), np.concatenate(ys), np.concatenate(cs)
    first = np.searchsorted(c, np.arange(base))
    same = c[1:] == c[:-1]
    seen = np.bincount(y[:-1][same] * 2 + y[1:][same], minlength=4).reshape(2, 2).astype(float)
    began = np.bincount(y[first].astype(int), minlength=2).astype(float)
    grad2 = np.full(1 << BITS, 1e-6)
    small2, start2 = np.full((2, 2), 1e-6), np.full(2, 1e-6)
    distinct = [np.ones(len(f), bool)] + [f[:, j] != f[:, 0] for j in range(1, f.shape[1])]
    for _ in range(rounds):  # penalised likelihood, adaptive steps
        p, two, starts = model.marginals(model.emission(f), c, pairs=True)
        g = -0.02 * model.weight.astype(np.float64)
        for j, ok in enumerate(distinct):
            g += np.bincount(f[ok, j], (y - p)[ok], minlength=1 << BITS)
        grad2 += g * g
        model.weight += (0.8 * g / np.sqrt(grad2)).astype(np.float32)
        for value, total, target, expected in ((model.step, small2, seen, two), (model.start, start2, began, starts)):
            d = target - expected - 0.1 * value
            total += d * d
            value += 0.3 * d / np.sqrt(total)
    model.weight[np.abs(model.weight) < 1e-3] = 0
    # logistic layer on the sample's marginals
    x = np.concatenate([model.summary(model.marginals(model.emission(feats), chain), w.text, end - row) for row, end, data, off in chunks(pa.array(texts, pa.string())) for w, feats, chain in [features(data, off)]])
    layer = np.zeros(3)
    share = np.where(toxic, 0.5 / toxic.sum(), 0.5 / (~toxic).sum()) * len(toxic)
    for _ in range(30):
        q = 1 / (1 + np.exp(-np.clip(x @ layer, -40, 40)))
        h = (x * (share * q * (1 - q))[:, None]).T @ x + 0.05 * np.eye(3)
        layer += np.linalg.solve(h, x.T @ (share * (toxic - q)) - 0.05 * layer)
    model.layer = layer
    return model


def training_sample(docs: DataFrame, labels: DataFrame, train: str, per_class: int, max_chars: int) -> tuple[list, np.ndarray]:
    """Texts and toxic flags; ``train``: SQL over ``doc_id``."""
    flags = labels.where("doc_id is not null and toxic is not null").where(train).groupBy("doc_id").agg(F.max(F.col("toxic") != 0).alias("toxic"))
    sizes = (("true", per_class), ("false", CLEAN * per_class))
    order = [F.xxhash64("doc_id"), F.col("doc_id")]
    few = [flags.where(f"toxic = {x}").orderBy(*order).limit(2 * n).collect() for x, n in sizes]
    wanted = [r for rows in few for r in rows]
    if not wanted:
        return [], np.zeros(0, bool)
    known = docs.sparkSession.createDataFrame([(r["doc_id"], r["toxic"]) for r in wanted], "doc_id bigint, toxic boolean")
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").where(F.length("text") <= max_chars).join(F.broadcast(known), "doc_id")
    took = [rows.where(f"toxic = {x}").orderBy(*order, "text").limit(n).collect() for x, n in sizes]
    both = [r for part in took for r in part]
    return [r["text"] for r in both], np.array([r["toxic"] for r in both], bool)


def train_model(docs: DataFrame, labels: DataFrame, train: str = "true", per_class: int = 1200, max_chars: int = 12_000, clean_share: int = 16) -> Model:
    return fit(*training_sample(docs, labels, train, per_class, max_chars), clean_share=clean_share)


def _score(model_b, spans_at: float | None):
    def run(batches):
        model: Model = model_b.value
        for batch in batches:
            scores, spans = [], []
            for row, end, data, off in chunks(batch.column(1)):
                w, feats, chain = features(data, off)
                p = model.marginals(model.emission(feats), chain)
                scores.append(model.score(model.summary(p, w.text, end - row)))
                if spans_at is not None:
                    out: list = [[] for _ in range(end - row)]
                    hit = np.flatnonzero(p >= spans_at)
                    for i in hit.tolist():
                        own, at = out[w.text[i]], off[w.text[i]]
                        if own and i - 1 == own[-1][2]:
                            own[-1][1:] = [int(w.end[i] - at), i]
                        else:
                            own.append([int(w.start[i] - at), int(w.end[i] - at), i])
                    spans += [[{"start": s[0], "stop": s[1]} for s in own] for own in out]
            cols = [batch.column(0), pa.array(np.concatenate(scores) if scores else np.zeros(0))]
            if spans_at is not None:
                cols.append(pa.array(spans, pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))))
            yield pa.RecordBatch.from_arrays(cols, ["doc_id", "score", "spans"][: len(cols)])

    return run


def score_documents(docs: DataFrame, model: Model, spans_at: float | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, score, and with ``spans_at`` the byte offsets [start, stop) in
    the UTF-8 text of runs of words at least so likely to be toxic."""
    src = bounded(docs).select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    kind = src.schema["doc_id"].dataType.simpleString()
    more = ", spans array<struct<start:bigint,stop:bigint>>" if spans_at is not None else ""
    return src.mapInArrow(_score(docs.sparkSession.sparkContext.broadcast(model), spans_at), f"doc_id {kind}, score double{more}")


def drop_toxic(docs: DataFrame, model: Model, threshold: float = 0.5, text_col: str = "text") -> DataFrame:
    """``docs`` without rows that score at least ``threshold``: one scan."""
    names = docs.columns
    at = names.index(text_col)
    model_b = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        held = model_b.value
        for batch in batches:
            keep = []
            for row, end, data, off in chunks(batch.column(at)):
                w, feats, chain = features(data, off)
                p = held.marginals(held.emission(feats), chain)
                keep.append(held.score(held.summary(p, w.text, end - row)) < threshold)
            if keep:
                yield batch.filter(pa.array(np.concatenate(keep)))

    plain = bounded(docs).toDF(*[f"c{i}" for i in range(len(names))])
    return plain.mapInArrow(run, plain.schema).toDF(*names)
