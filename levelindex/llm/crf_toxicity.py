"""Toxicity: a two-state linear-chain conditional random field over words.

Labels are given for documents only, so token labels come first: in a toxic document the words
whose form or beginning occurs in toxic documents and practically never in others are labelled
toxic, all other words are not.  The field has features of a word (its form and
beginnings) and transition weights, all fitted by gradient ascent of the labels' likelihood (observed
less expected counts); forward-backward marginals give each word's probability.  A document's
score is a logistic function of the largest marginal, the sum and the mean; offending offsets are
the words with a marginal of one half or more.

The chain of a whole batch is walked as blocks of 2 x 2 matrices: products within all blocks at
once, then over blocks, then the messages.  A document's first word has a matrix that forgets what
was before, so texts of any length are exact and cost the same per word.

The fit uses at most `train_documents` toxic and `train_others` other rows, and `train_runs` runs of
words of either kind.  Cases: null and empty texts have no
words and get the score of zero evidence; null keys are held out; without toxic labels every score
is 0; repeated rows are scored separately.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelindex.llm.common import LOWER_TABLE, fold, id_and_text, raw_texts, small_batches, tidy

EDGE = b".,;:!?\"'()[]{}<>|#$%&*-_/\\+=~`^@"
BLOCK = 128
MEMO = 250_000


@dataclass(frozen=True)
class CrfSettings:
    train_documents: int = 1500
    train_others: int = 3500
    run: int = 256
    rounds: int = 25
    rate: float = 0.5
    move_rate: float = 0.1
    decay: float = 1e-6
    train_runs: int = 1800
    least_surprise: float = 4.0
    least_ratio: float = 15.0
    seed: int = 5


def forms(token: bytes) -> list[bytes]:
    """Feature names of a word: its form and its beginnings of 4 to 6 bytes."""
    w = token.translate(LOWER_TABLE).strip(EDGE)
    return [b"=" + w] + [b"<" + w[:n] for n in (4, 5, 6) if len(w) >= n]


class Emissions(dict):
    """Log-odds that words alone give; the first ones seen are kept, up to a fixed number."""

    def __init__(self, chain: "Chain"):
        super().__init__()
        self.chain = chain

    def __missing__(self, token: bytes) -> float:
        w = self.chain.weights
        found = self.chain.bias + sum([w.get(f, 0.0) for f in forms(token)])
        if len(self) < MEMO and len(token) <= 48:
            self[token] = found
        return found


class Chain:
    """Word weights, transitions and the calibration of document scores."""

    def __init__(self, weights: dict[bytes, float], bias: float, move: np.ndarray, start: np.ndarray, scale: np.ndarray):
        self.weights, self.bias, self.move, self.start, self.scale = weights, bias, move, start, scale
        self.memo = Emissions(self)


    def marginals(self, emissions: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Probability of the toxic state for each word of texts laid end to end; `starts` marks first words."""
        return self.walk(emissions, starts)[0]

    def walk(self, emissions: np.ndarray, starts: np.ndarray, moves: bool = False) -> tuple[np.ndarray, np.ndarray]:
        """The marginals, and with `moves` the expected number of moves from each state to each within texts."""
        n = len(emissions)
        expected = np.zeros((2, 2))
        if not n:
            return np.zeros(0), expected
        rows = -(-n // BLOCK)
        up = np.exp(np.clip(emissions, -40, 40))
        gate = np.stack([np.ones(n), up], axis=1)
        step = np.where(starts[:, None, None], np.broadcast_to(self.start, (2, 2)), self.move) * gate[:, None, :]
        step = np.concatenate([step, np.broadcast_to(np.eye(2), (rows * BLOCK - n, 2, 2))]).reshape(rows, BLOCK, 2, 2)
        product = np.broadcast_to(np.eye(2), (rows, 2, 2)).copy()
        for j in range(BLOCK):
            product = product @ step[:, j]
            product /= product.max(axis=(1, 2), keepdims=True)
        ahead, behind = np.empty((rows, 2)), np.empty((rows, 2))
        v = np.array([1.0, 0.0])
        for i in range(rows):
            ahead[i] = v
            v = v @ product[i]
            v /= v.sum()
        v = np.ones(2)
        for i in range(rows - 1, -1, -1):
            behind[i] = v
            v = product[i] @ v
            v /= v.sum()
        alpha = np.empty((rows, BLOCK, 2))
        first = ahead
        inside = np.concatenate([~starts, np.zeros(rows * BLOCK - n, bool)]).reshape(rows, BLOCK)
        for j in range(BLOCK):
            ahead = np.einsum("ri,rij->rj", ahead, step[:, j])
            ahead /= ahead.sum(axis=1, keepdims=True)
            alpha[:, j] = ahead
        for j in range(BLOCK - 1, -1, -1):
            if moves:
                pair = (alpha[:, j - 1] if j else first)[:, :, None] * step[:, j] * behind[:, None, :]
                expected += (pair / pair.sum(axis=(1, 2), keepdims=True))[inside[:, j]].sum(axis=0)
            alpha[:, j] *= behind
            behind = np.einsum("rij,rj->ri", step[:, j], behind)
            behind /= behind.sum(axis=1, keepdims=True)
        both = alpha.reshape(-1, 2)[:n]
        return both[:, 1] / both.sum(axis=1), expected

    def evidence(self, texts: list[bytes]) -> tuple[np.ndarray, list[list[bytes]], np.ndarray]:
        """Per text: largest, summed and mean marginal; then its words; then all marginals."""
        words = [t.split() for t in texts]
        sizes = np.array([len(w) for w in words], int)
        total = int(sizes.sum())
        emissions = np.fromiter(map(self.memo.__getitem__, chain.from_iterable(words)), float, total)
        starts = np.zeros(total, bool)
        begins = (np.cumsum(sizes) - sizes)[sizes > 0]
        starts[begins] = True
        m = self.marginals(emissions, starts)
        out = np.zeros((len(texts), 3))
        if total:
            has = sizes > 0
            out[has, 0] = np.maximum.reduceat(m, begins)
            out[has, 1] = np.log1p(np.add.reduceat(m, begins))
            out[has, 2] = np.add.reduceat(m, begins) / sizes[has]
        return out, words, m

    def scores(self, evidence: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-(evidence @ self.scale[:3] + self.scale[3])))


def token_labels(texts: list[bytes], toxic: list[int], settings: CrfSettings) -> set[bytes]:
    """Feature names of words that mark toxic documents; copies of a document (by one min-hash) count once."""
    merged: dict[tuple[int, int], set[bytes]] = {}
    for text, y in zip(texts, toxic):
        if words := set(text.split()):
            merged.setdefault((y, min(map(zlib.crc32, words))), set()).update(words)
    inside: Counter = Counter()
    for (y, _), words in merged.items():
        if y:
            inside.update({f for w in words for f in forms(w)})
    counts = ({}, {f: c for f, c in inside.items() if c >= 3})
    del inside
    for (y, _), words in merged.items():
        if not y:
            for f in {f for w in words for f in forms(w) if f in counts[1]}:
                counts[0][f] = counts[0].get(f, 0) + 1
    toxic = [y for y, _ in merged]
    n1 = sum(toxic)
    n0 = len(toxic) - n1
    if not n0 or not n1:
        return set()
    signs = set()
    least = settings.least_surprise + np.log(len(counts[1]) + 1)  # so that few features pass by chance
    for f, c1 in counts[1].items():
        c0 = counts[0].get(f, 0)
        both = c1 + c0
        surprise = c1 * np.log(c1 * len(toxic) / (both * n1)) + (c0 * np.log(c0 * len(toxic) / (both * n0)) if c0 else 0)
        if surprise >= least and c1 * n0 >= settings.least_ratio * (c0 + 0.5) * n1:
            signs.add(f)
    return signs


def fit(texts: list[bytes], toxic: list[int], settings: CrfSettings) -> Chain | None:
    """Gradient ascent of the labels' likelihood, then the calibration; None without both labels."""
    if not texts or min(toxic) == max(toxic):
        return None
    signs = token_labels(texts, toxic, settings)
    known = {w for text, y in zip(texts, toxic) if y for w in set(text.split()) if any(f in signs for f in forms(w))}
    told, rest = [], []  # (text, place, label) of runs with a sign in a toxic text, and of the others
    for i, (text, y) in enumerate(zip(texts, toxic)):
        words = text.split()
        for at in range(0, len(words), settings.run):
            (told if y and not known.isdisjoint(words[at : at + settings.run]) else rest).append((i, at, y))
    draw = np.random.default_rng(settings.seed)
    chosen = told[: settings.train_runs] + [rest[i] for i in draw.permutation(len(rest))[: settings.train_runs]]
    if not chosen:
        return None
    kinds: dict[bytes, int] = {}
    runs, marks = [], [y for _, _, y in chosen]
    for i, at, _ in chosen:
        words = texts[i].split()[at : at + settings.run]
        runs.append(np.fromiter((kinds.setdefault(w, len(kinds)) for w in words), int, len(words)))
    signed = np.array([w in known for w in kinds])
    names: dict[bytes, int] = {}
    features = [[names.setdefault(f, len(names)) for f in forms(w)] for w in kinds]
    flat = np.concatenate(runs)
    starts = np.zeros(len(flat), bool)
    sizes = np.array([len(r) for r in runs])
    starts[np.cumsum(sizes) - sizes] = True
    y = signed[flat] & np.repeat(np.array(marks, bool), sizes)
    owner = np.repeat(np.arange(len(kinds)), [len(f) for f in features])
    slot = np.concatenate([np.array(f) for f in features])
    weights = np.zeros(len(names))
    bias = -4.0
    seen = np.zeros((2, 2))
    inner = ~starts[1:]
    np.add.at(seen, (y[:-1][inner].astype(int), y[1:][inner].astype(int)), 1)
    move = np.log((seen + 1) / (seen + 1).sum(axis=1, keepdims=True))  # where the fit begins
    start = np.array([1 - y.mean(), y.mean()]) + 1e-4
    g2, gm = np.full(len(names), 1e-8), np.full((2, 2), 1e-8)
    gb = 1e-8
    for _ in range(settings.rounds):
        by_kind = np.bincount(owner, weights=weights[slot], minlength=len(kinds)) + bias
        m, expected = Chain({}, bias, np.exp(move), start, np.zeros(4)).walk(by_kind[flat], starts, moves=True)
        gap = np.bincount(flat, weights=y - m, minlength=len(kinds))
        grad = np.bincount(slot, weights=gap[owner], minlength=len(names)) - settings.decay * weights
        g2 += grad * grad
        weights = weights + settings.rate * grad / np.sqrt(g2)
        total = gap.sum()
        gb += total * total
        bias += settings.rate * total / np.sqrt(gb)
        more = seen - expected
        gm += more * more
        move = move + settings.move_rate * more / np.sqrt(gm)
    told = {f: float(weights[i]) for f, i in names.items() if abs(weights[i]) > 0.02}
    fitted = Chain(told, bias, np.exp(move), start, np.zeros(4))
    evidence = np.concatenate([fitted.evidence(texts[i : i + 256])[0] for i in range(0, len(texts), 256)])
    fitted.scale = calibrate(evidence, np.array(toxic, float))
    return fitted


def calibrate(evidence: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Newton steps of a ridge logistic regression."""
    x = np.column_stack([evidence, np.ones(len(y))])
    b = np.zeros(4)
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(x @ b, -30, 30)))
        h = x.T @ (x * (p * (1 - p) + 1e-6)[:, None]) + 0.05 * np.eye(4)
        b += np.linalg.solve(h, x.T @ (y - p) - 0.05 * b)
    return b


def labelled_texts(rows: DataFrame, labels: DataFrame, train, settings: CrfSettings, id_col: str = "doc_id") -> list[tuple[bytes, int]]:
    known = labels.select(labels[id_col].cast("long").alias("doc_id"), labels["toxic"].cast("int").alias("y")).where(F.col("y").isin(0, 1) & train(F.col("doc_id"))).groupBy("doc_id").agg(F.max("y").alias("y"))
    some = lambda y: known.where(F.col("y") == y).orderBy(F.xxhash64("doc_id", F.lit(settings.seed)), "doc_id").limit(settings.train_documents if y else settings.train_others)
    joined = rows.join(F.broadcast(some(0).unionAll(some(1))), "doc_id").orderBy("doc_id", F.xxhash64("text")).limit(settings.train_documents + settings.train_others)
    return [(r.text.encode(), r.y) for r in joined.select("text", "y").toLocalIterator()]


def spans_of(text: bytes, words: list[bytes], marginals: np.ndarray) -> list[dict[str, int]]:
    """Character offsets of the words whose marginal is at least one half."""
    if not (marginals >= 0.5).any():
        return []
    out, at, chars = [], 0, 0
    for i, place in enumerate(re.finditer(rb"\S+", text)):
        if marginals[i] >= 0.5:
            begin, end = place.span()
            chars += len(text[at:begin].decode("utf-8", "replace"))
            size = len(words[i].decode("utf-8", "replace"))
            out.append({"begin": chars, "end": chars + size})
            at, chars = end, chars + size
    return out


def toxicity_scores(docs: DataFrame, labels: DataFrame, settings: CrfSettings = CrfSettings(), mod: int = 3, held: int = 1, threshold: float = 0.7, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, score, predicted and offending spans (characters) of every row."""
    rows = id_and_text(docs, id_col, text_col)
    sample = labelled_texts(rows, labels, lambda c: fold(c, mod) != held, settings)
    model = fit([t for t, _ in sample], [y for _, y in sample], settings)
    scored = tag(rows, model, threshold)
    return scored.select("doc_id", F.coalesce(fold(F.col("doc_id"), mod) == held, F.lit(True)).alias("held_out"), "score", "predicted", "spans")


def tag(rows: DataFrame, model: Chain | None, threshold: float) -> DataFrame:
    """Score and tag rows of doc_id and text by a fitted chain."""
    sent = rows.sparkSession.sparkContext.broadcast(None if model is None else (model.weights, model.bias, model.move, model.start, model.scale))
    place = pa.list_(pa.struct([("begin", pa.int32()), ("end", pa.int32())]))

    def run(batches):
        own = None if sent.value is None else Chain(*sent.value)
        for batch in small_batches(batches, "text", 2 << 20):
            texts = raw_texts(batch.column("text"))
            if own is None:
                score, spans = np.zeros(len(texts)), [[] for _ in texts]
            else:
                evidence, words, m = own.evidence(texts)
                score, spans, at = own.scores(evidence), [], 0
                for text, w in zip(texts, words):
                    spans.append(spans_of(text, w, m[at : at + len(w)]))
                    at += len(w)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(score), pa.array((score >= threshold).astype(np.int32)), pa.array(spans, place)], ["doc_id", "score", "predicted", "spans"])
        del own
        tidy()

    return rows.select("doc_id", "text").mapInArrow(run, "doc_id long, score double, predicted int, spans array<struct<begin:int,end:int>>")
