"""Quality classifier: gated attention over encoded passages, learned from document labels.

A text is cut into passages of `passage_bytes` bytes.  Each is encoded by shares of hashed byte
pairs and a few ratios (letter case, signs, digits, repeated words), then by one dense layer.
Nothing is counted across the end of a passage; what is told of the whole text (its length, the
shares of distinct words and triples of words) comes from one pass over all of it, so a text has the
same features whatever stands beside it and however many groups of passages it fills.
A gated attention unit gives every passage a weight; the weighted sum of passages is scored.
Only document labels are used: the passage weights are learned.

The fit uses at most `train_documents` labelled rows, picked by a hash of their key, with their whole
texts: the first `kept_passages` passages stay encoded, those of further documents are encoded again
when their turn comes.  Scoring reads whole texts; passages go through in groups with a running
softmax, so a text of any length takes bounded memory.  Cases: null and empty texts are one empty passage; null keys are held out; several
rows of a key are scored separately; without labels every score is 0.5.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelindex.llm.common import fold, id_and_text, raw_texts, small_batches

BUCKETS = 512
EXTRAS = 12
WIDTH = BUCKETS + EXTRAS
#: Words and triples of a text are told apart by so many bits of a hash.
MARKS = 20
HIGH = np.arange(256) >= 128
MIX = np.random.default_rng(3).integers(1, 1 << 40, 64)
SPACE = np.isin(np.arange(256), [32, 9, 10, 11, 12, 13])
UPPER = (np.arange(256) >= 65) & (np.arange(256) <= 90)
DIGIT = (np.arange(256) >= 48) & (np.arange(256) <= 57)
SIGN = (np.arange(256) > 32) & (np.arange(256) < 127) & ~np.char.isalnum(np.array([chr(i) for i in range(256)]))


@dataclass(frozen=True)
class MilSettings:
    passage_bytes: int = 512
    group: int = 512
    train_documents: int = 4000
    kept_passages: int = 32_768
    hidden: int = 24
    attention: int = 12
    epochs: int = 8
    batch: int = 64
    rate: float = 0.004
    decay: float = 1e-4
    seed: int = 11


def word_codes(raw: np.ndarray, edges: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First bytes of the words of passages that begin at `edges`, and their hashes."""
    space = SPACE[raw]
    fresh = np.ones(len(raw), bool)
    fresh[1:] = space[:-1]
    fresh[edges] = True
    first = ~space & fresh
    begins = np.flatnonzero(first)
    if not len(begins):
        return begins, begins
    position = np.arange(len(raw), dtype=np.int32)
    position -= np.maximum.accumulate(np.where(first, position, 0))
    return begins, np.add.reduceat(np.where(space, 0, raw.astype(np.int64)) * MIX[position & 63], begins) & 0xFFFFFFFF


def marks(code: np.ndarray) -> np.ndarray:
    return (code * 2654435761 & 0xFFFFFFFF) >> (32 - MARKS)


def triples(code: np.ndarray) -> np.ndarray:
    return code[2:] * 31 + code[1:-1] * 17 + code[:-2] & 0xFFFFFFFF


def text_features(raw: np.ndarray, length: int, group: int) -> np.ndarray:
    """Distinct words and triples by words and the length of one text, read in groups of passages."""
    seen = np.zeros((2, 1 << MARKS), bool)
    words, last = 0, np.zeros(0, np.int64)
    for at in range(0, len(raw), length * group):
        piece = raw[at : at + length * group]
        _, code = word_codes(piece, np.arange(0, len(piece), length))
        words += len(code)
        last = np.concatenate([last, code])
        seen[0, marks(code)] = True
        seen[1, marks(triples(last))] = True
        last = last[-2:]
    return np.array([*(seen.sum(axis=1) / max(words, 1)), np.log1p(len(raw)) / 10])


def encode_passages(texts: list[np.ndarray], length: int, known: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Feature rows of all passages of some texts, and how many each text has; `known` has the features
    of the whole text that the (single) given piece belongs to."""
    bytes_of = np.array([len(t) for t in texts])
    sizes = np.maximum(1, -(-bytes_of // length))
    n = int(sizes.sum())
    out = np.zeros((n, WIDTH), np.float32)
    raw = np.concatenate(texts) if len(texts) else np.zeros(0, np.uint8)
    doc_of_passage = np.repeat(np.arange(len(texts)), sizes)
    out[:, BUCKETS + 10] = np.log1p(bytes_of)[doc_of_passage] / 10
    out[:, BUCKETS + 7], out[:, BUCKETS + 11] = 0.01, 1 / length
    if known is not None:
        out[:, BUCKETS + 8 : BUCKETS + 11] = known
    if not len(raw):
        return out, sizes
    begin = np.cumsum(bytes_of) - bytes_of
    some = bytes_of > 0
    edges = np.concatenate([np.arange(0, m, length) + b for m, b in zip(bytes_of[some], begin[some])])
    owners = np.flatnonzero(bytes_of[doc_of_passage] > 0)
    held = np.diff(np.append(edges, len(raw)))
    where = np.repeat(owners.astype(np.int32), held)
    filled = np.ones(n, np.float32)
    filled[owners] = held
    wide = raw.astype(np.int32)
    pair = (wide[:-1] * 131 + wide[1:] * 7 ^ wide[1:] >> 3) & (BUCKETS - 1)
    inner = where[:-1] == where[1:]
    out[:, :BUCKETS] = np.sqrt(np.bincount(where[:-1][inner] * np.int64(BUCKETS) + pair[inner], minlength=n * BUCKETS).reshape(n, BUCKETS) / filled[:, None])
    for i, mask in enumerate((UPPER, DIGIT, SIGN, SPACE, HIGH)):
        out[owners, BUCKETS + i] = np.add.reduceat(mask[raw], edges, dtype=np.int32) / held
    out[:, BUCKETS + 11] = filled / length
    begins, code = word_codes(raw, edges)
    if not len(begins):
        return out, sizes
    at = where[begins].astype(np.int64)
    words = np.maximum(np.bincount(at, minlength=n), 1)
    same = np.zeros(len(code))
    same[1:] = (code[1:] == code[:-1]) & (at[1:] == at[:-1])
    out[:, BUCKETS + 5] = np.bincount(at, weights=same, minlength=n) / words
    out[:, BUCKETS + 6] = np.bincount(np.unique(at << 32 | code) >> 32, minlength=n) / words
    out[:, BUCKETS + 7] = words / 100.0
    if known is None:
        doc = doc_of_passage[at]
        in_doc = np.maximum(np.bincount(doc, minlength=len(texts)), 1)
        whole = doc[2:] == doc[:-2]
        for i, values, owner in ((8, code, doc), (9, triples(code)[whole], doc[2:][whole])):
            out[:, BUCKETS + i] = (np.bincount(np.unique(owner << MARKS | marks(values)) >> MARKS, minlength=len(texts)) / in_doc)[doc_of_passage]
    return out, sizes


class AttentionMil:
    """Dense encoder, gated attention, logistic output."""

    NAMES = ("w", "b", "v", "u", "a", "c", "d")

    def __init__(self, params: dict[str, np.ndarray], mean: np.ndarray, spread: np.ndarray):
        self.p, self.mean, self.spread = params, mean, spread

    @classmethod
    def fresh(cls, settings: MilSettings, mean: np.ndarray, spread: np.ndarray) -> "AttentionMil":
        draw = np.random.default_rng(settings.seed)
        h, k = settings.hidden, settings.attention
        g = lambda *s: draw.normal(0, 1 / np.sqrt(s[0]), s)
        return cls({"w": g(WIDTH, h), "b": np.zeros(h), "v": g(h, k), "u": g(h, k), "a": g(k), "c": g(h), "d": np.zeros(1)}, mean, spread)

    def ready(self) -> "AttentionMil":
        """Fold the scaling of the inputs into the first layer, once per worker."""
        self.w = (self.p["w"] / self.spread[:, None]).astype(np.float32)
        self.b = (self.p["b"] - self.mean / self.spread @ self.p["w"]).astype(np.float32)
        return self

    def passages(self, texts: list[np.ndarray], settings: MilSettings, known: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Hidden vectors, attention scores, passages per text."""
        x, sizes = encode_passages(texts, settings.passage_bytes, known)
        h = np.tanh(x @ self.w + self.b).astype(float)
        return h, (np.tanh(h @ self.p["v"]) / (1 + np.exp(-(h @ self.p["u"])))) @ self.p["a"], sizes

    def output(self, z: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-(z @ self.p["c"] + self.p["d"][0])))

    def pieces(self, raw: np.ndarray, settings: MilSettings):
        """Hidden vectors and attention scores of one whole text, group by group."""
        known = text_features(raw, settings.passage_bytes, settings.group)
        step = settings.passage_bytes * settings.group
        for at in range(0, max(len(raw), 1), step):
            h, s, _ = self.passages([raw[at : at + step]], settings, known)
            yield h, s

    def score(self, raw: np.ndarray, settings: MilSettings) -> float:
        """Score of one whole text, in groups of passages with a running softmax."""
        top, total, pooled = -np.inf, 0.0, np.zeros(settings.hidden)
        for h, s in self.pieces(raw, settings):
            new = max(top, float(s.max()))
            keep, e = np.exp(top - new), np.exp(s - new)
            total, pooled, top = total * keep + e.sum(), pooled * keep + e @ h, new
        return float(self.output(pooled / total))

    def score_many(self, texts: list[np.ndarray], settings: MilSettings) -> np.ndarray:
        """Scores of whole texts: short ones together, longer ones by `score`."""
        out = np.empty(len(texts))
        most = settings.passage_bytes * settings.group
        group, held = [], 0
        for i, t in enumerate([*texts, None]):
            if t is not None and len(t) > most:
                out[i] = self.score(t, settings)
                continue
            if group and (t is None or held + len(t) > 4 * most):
                h, s, sizes = self.passages([texts[j] for j in group], settings)
                begins = np.cumsum(sizes) - sizes
                e = np.exp(s - np.repeat(np.maximum.reduceat(s, begins), sizes))
                out[group] = self.output(np.add.reduceat(h * e[:, None], begins) / np.add.reduceat(e, begins)[:, None])
                group, held = [], 0
            if t is not None:
                group.append(i)
                held += len(t)
        return out

    def gradients(self, x: np.ndarray, sizes: np.ndarray, y: np.ndarray, of: int | None = None) -> dict[str, np.ndarray]:
        """Of the logistic loss of some documents over `of` (their number); `x` has their passages in order."""
        p = self.p
        begins = np.cumsum(sizes) - sizes
        doc = np.repeat(np.arange(len(sizes)), sizes)
        h = np.tanh(x @ p["w"] + p["b"])
        t, g = np.tanh(h @ p["v"]), 1 / (1 + np.exp(-(h @ p["u"])))
        s = (t * g) @ p["a"]
        e = np.exp(s - np.repeat(np.maximum.reduceat(s, begins), sizes))
        w = e / np.repeat(np.add.reduceat(e, begins), sizes)
        z = np.add.reduceat(h * w[:, None], begins)
        out = (1 / (1 + np.exp(-(z @ p["c"] + p["d"]))) - y) / (of or len(y))
        dz = out[:, None] * p["c"]
        dw = (h * dz[doc]).sum(axis=1)
        ds = w * (dw - np.add.reduceat(w * dw, begins)[doc])
        dt, dg = ds[:, None] * p["a"] * g * (1 - t * t), ds[:, None] * p["a"] * t * g * (1 - g)
        dh = w[:, None] * dz[doc] + dt @ p["v"].T + dg @ p["u"].T
        pre = dh * (1 - h * h)
        return {"w": x.T @ pre, "b": pre.sum(axis=0), "v": h.T @ dt, "u": h.T @ dg, "a": (t * g).T @ ds, "c": z.T @ out, "d": out.sum(keepdims=True)}


    def long_gradients(self, raw: np.ndarray, y: float, of: int, settings: MilSettings) -> dict[str, np.ndarray]:
        """The same for one document of any length: a pass for the attention, one for the gradients."""
        p, step = self.p, settings.passage_bytes * settings.group
        known = text_features(raw, settings.passage_bytes, settings.group)

        def parts():
            for at in range(0, max(len(raw), 1), step):
                x = (encode_passages([raw[at : at + step]], settings.passage_bytes, known)[0] - self.mean) / self.spread
                h = np.tanh(x @ p["w"] + p["b"])
                t, g = np.tanh(h @ p["v"]), 1 / (1 + np.exp(-(h @ p["u"])))
                yield x, h, t, g, (t * g) @ p["a"]

        top, total, pooled = -np.inf, 0.0, np.zeros(settings.hidden)
        for _, h, _, _, s in parts():
            new = max(top, float(s.max()))
            keep, e = np.exp(top - new), np.exp(s - new)
            total, pooled, top = total * keep + e.sum(), pooled * keep + e @ h, new
        z = pooled / total
        out = (1 / (1 + np.exp(-(z @ p["c"] + p["d"][0]))) - y) / of
        dz = out * p["c"]
        grads = {k: np.zeros_like(v) for k, v in p.items()}
        grads["c"], grads["d"] = out * z, np.array([out])
        for x, h, t, g, s in parts():
            w = np.exp(s - top) / total
            ds = w * (h @ dz - z @ dz)
            dt, dg = ds[:, None] * p["a"] * g * (1 - t * t), ds[:, None] * p["a"] * t * g * (1 - g)
            pre = (w[:, None] * dz + dt @ p["v"].T + dg @ p["u"].T) * (1 - h * h)
            for k, more in (("w", x.T @ pre), ("b", pre.sum(axis=0)), ("v", h.T @ dt), ("u", h.T @ dg), ("a", (t * g).T @ ds)):
                grads[k] += more
        return grads


def fit(texts: list[bytes], labels: list[int], settings: MilSettings) -> AttentionMil | None:
    """Adam over shuffled batches of documents; None if there is just one label."""
    y = np.array(labels, float)
    if not len(y) or y.min() == y.max():
        return None
    raw = [np.frombuffer(t, np.uint8) for t in texts]
    lengths = np.maximum(1, -(-np.array([len(t) for t in raw]) // settings.passage_bytes))
    kept = (np.cumsum(lengths) <= settings.kept_passages) & (lengths <= settings.group)
    if not kept.any():
        kept[lengths.argmin()] = True
    flat, sizes = encode_passages([t for t, k in zip(raw, kept) if k], settings.passage_bytes)
    mean, spread = flat.mean(axis=0), flat.std(axis=0) + 0.01
    flat -= mean
    flat /= spread
    begins = np.cumsum(sizes) - sizes
    row = np.cumsum(kept) - 1
    model = AttentionMil.fresh(settings, mean, spread)
    draw = np.random.default_rng(settings.seed)
    m = {k: np.zeros_like(v) for k, v in model.p.items()}
    s = {k: np.zeros_like(v) for k, v in model.p.items()}
    step = 0
    for epoch in range(settings.epochs):
        rate = settings.rate * (0.5 if epoch > settings.epochs * 0.6 else 1)
        for some in np.array_split(draw.permutation(len(y)), max(1, len(y) // settings.batch)):
            held = some[kept[some]]
            grads = {k: np.zeros_like(v) for k, v in model.p.items()}
            if len(held):
                at = np.concatenate([np.arange(begins[i], begins[i] + sizes[i]) for i in row[held]])
                grads = model.gradients(flat[at], sizes[row[held]], y[held], len(some))
            for i in some[~kept[some]]:
                grads = {k: grads[k] + v for k, v in model.long_gradients(raw[i], y[i], len(some), settings).items()}
            step += 1
            for k, grad in grads.items():
                grad = grad + settings.decay * model.p[k]
                m[k] = 0.9 * m[k] + 0.1 * grad
                s[k] = 0.999 * s[k] + 0.001 * grad * grad
                model.p[k] = model.p[k] - rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(s[k] / (1 - 0.999**step)) + 1e-8)
    return model.ready()


def labelled_sample(rows: DataFrame, labels: DataFrame, label: str, train, limit: int, seed: int, id_col: str = "doc_id") -> list[tuple[bytes, int]]:
    """At most `limit` labelled texts outside the held-out fold, the same ones each time."""
    known = labels.select(labels[id_col].cast("long").alias("doc_id"), labels[label].cast("int").alias("y")).where(F.col("y").isin(0, 1) & train(F.col("doc_id")))
    picked = known.groupBy("doc_id").agg(F.max("y").alias("y")).orderBy(F.xxhash64("doc_id", F.lit(seed)), "doc_id").limit(limit)
    joined = rows.join(F.broadcast(picked), "doc_id").orderBy("doc_id", F.xxhash64("text")).limit(limit)
    return [(r.text.encode(), r.y) for r in joined.select("text", "y").toLocalIterator()]


def quality_scores(docs: DataFrame, labels: DataFrame, settings: MilSettings = MilSettings(), mod: int = 5, held: int = 0, threshold: float = 0.3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, score, predicted for every row."""
    rows = id_and_text(docs, id_col, text_col)
    sample = labelled_sample(rows, labels, "quality", lambda c: fold(c, mod) != held, settings.train_documents, settings.seed)
    model = fit([t for t, _ in sample], [y for _, y in sample], settings)
    sent = docs.sparkSession.sparkContext.broadcast(None if model is None else (model.p, model.mean, model.spread))

    def run(batches):
        own = None if sent.value is None else AttentionMil(*sent.value).ready()
        for batch in small_batches(batches, "text"):
            texts = [np.frombuffer(t, np.uint8) for t in raw_texts(batch.column("text"))]
            score = np.full(len(texts), 0.5) if own is None else own.score_many(texts, settings)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(score), pa.array((score >= threshold).astype(np.int32))], ["doc_id", "score", "predicted"])

    scored = rows.mapInArrow(run, "doc_id long, score double, predicted int")
    return scored.select("doc_id", F.coalesce(fold(F.col("doc_id"), mod) == held, F.lit(True)).alias("held_out"), "score", "predicted")
