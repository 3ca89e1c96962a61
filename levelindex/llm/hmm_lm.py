"""Hidden Markov language model: Baum-Welch over partitions, exact scaled forward scores.

States emit word classes; a class then gives the word.  Words that make up at least one in
`own_classes` of all training tokens are classes by themselves (so there are at most that many), all others
share `shape_classes` classes by their first and last bytes.  Within a shape class a word has the
probability (c + 0.5) / (M + 0.5 V + 0.5) with c its training count and M, V the class's tokens and
distinct words; the rest, 0.5 over the same sum, is the class's unknown word.  So the model's size
is fixed while the counts it rests on cover every training token.

Words whose share of the training tokens is at least 1 / `cached_words` (at most that many) go to the workers
as a table; all rarer words meet their counts in a shuffled join, pre-summed by document.

Training starts from a bounded sample of whole documents (`warm_documents`) on the driver; after that
each Baum-Welch round runs over every training document and sums expected counts over partitions.
Documents are laid out in runs of `train_run` tokens; the messages that enter a run from both sides
are carried over from its neighbours, so expected counts are those of whole documents.  Classes, counts
and the cut between cached and rarer words come from training documents alone.

Cases: null text is empty and has the end token only; null keys are held out; an empty training set
leaves N = 0 and every word unknown; repeated rows are scored separately.
"""

from __future__ import annotations

import zlib
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelindex import scratch
from levelindex.llm.common import LOWER_TABLE, by_length, fold, id_and_text, raw_texts, small_batches

LONGEST_CACHED = 64
LOG_HALF = float(np.log10(0.5))


@dataclass(frozen=True)
class HmmSettings:
    states: int = 8
    own_classes: int = 8192
    shape_classes: int = 4096
    cached_words: int = 262_144
    warm_documents: int = 2000
    warm_rounds: int = 12
    rounds: int = 3
    train_run: int = 2048
    smoothing: float = 1000.0
    seed: int = 7


def words_of(text: bytes) -> list[bytes]:
    """A-Z lowered; maximal runs of bytes other than the six ASCII white spaces."""
    return text.translate(LOWER_TABLE).split()


def shape(word: bytes, n: int) -> int:
    return zlib.crc32(word[:4] + b" " + word[-4:]) % n


def count_words(train: DataFrame) -> DataFrame:
    """word, in_train for every word of the training documents."""

    def run(batches):
        counts = Counter()

        def flush():
            out = pa.RecordBatch.from_arrays([pa.array(list(counts), pa.binary()), pa.array(list(counts.values()), pa.int64())], ["word", "in_train"])
            counts.clear()
            return out

        for batch in small_batches(batches, "text"):
            for text in raw_texts(batch.column("text")):
                counts.update(words_of(text))
            if len(counts) > 400_000:
                yield flush()
        if counts:
            yield flush()

    return train.select("text").mapInArrow(run, "word binary, in_train long").groupBy("word").agg(F.sum("in_train").alias("in_train"))


class Classes:
    """Word classes and cached counts, small enough for every worker."""

    def __init__(self, settings: HmmSettings, own: list[bytes], cached: dict[bytes, int], mass: np.ndarray, end_count: int):
        self.settings, self.cached, self.end_count = settings, cached, end_count
        self.own = {w: i + 1 for i, w in enumerate(own)}  # class 0 is the end
        self.first_shape = len(own) + 1
        self.size = self.first_shape + settings.shape_classes
        self.log_mass = np.log10(mass)  # of the shape classes
        words = list(cached)
        counts = np.array([cached[w] for w in words], float)
        # Each cached word is a number; the arrays give its class, log10(c + 0.5) and whether c > 0.
        self.numbers = Numbers({w: i for i, w in enumerate(words)}, self)
        self.class_of = np.array([self.class_number(w) for w in words], np.int64)
        self.log_of, self.known = np.log10(counts + 0.5), counts > 0

    def class_number(self, word: bytes) -> int:
        own = self.own.get(word)
        return self.first_shape + shape(word, self.settings.shape_classes) if own is None else own


class Numbers(dict):
    """Numbers of cached words; any other word gives -1 minus its class."""

    def __init__(self, numbers: dict[bytes, int], classes: Classes):
        super().__init__(numbers)
        self.classes = classes

    def __missing__(self, word: bytes) -> int:
        return -1 - self.classes.class_number(word)

    def __reduce__(self):
        return Numbers, (dict(self), self.classes)


def class_mass(vocabulary: DataFrame, own: set[bytes], settings: HmmSettings) -> np.ndarray:
    """M + 0.5 V + 0.5 of every shape class, over all training words."""
    n = settings.shape_classes

    def run(batches):
        total = np.zeros(n)
        for batch in batches:
            for word, c in zip(batch.column("word").to_pylist(), batch.column("in_train").to_pylist()):
                if c and word not in own:
                    total[shape(word, n)] += c + 0.5
        yield pa.RecordBatch.from_arrays([pa.array(range(n), pa.int32()), pa.array(total)], ["class", "mass"])

    rows = vocabulary.select("word", "in_train").mapInArrow(run, "class int, mass double").groupBy("class").agg(F.sum("mass").alias("mass")).collect()
    mass = np.full(n, 0.5)
    for r in rows:
        mass[r["class"]] += r["mass"]
    return mass


def encode(docs: DataFrame, classes) -> DataFrame:
    """One row a document: sums over cached words, the class sequence, and the rarer words with their frequency."""
    schema = pa.schema([("uid", pa.int64()), ("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("counted", pa.float64()), ("within", pa.float64()), ("n_rare", pa.int64()), ("classes", pa.binary()), ("rare", pa.list_(pa.binary())), ("rare_n", pa.list_(pa.int32()))])

    def run(batches):
        model = classes.value
        uid = TaskContext.get().partitionId() << 36
        numbers, first, log_end = model.numbers, model.first_shape, float(np.log10(model.end_count + 0.5))
        for batch in small_batches(batches, "text", 2 << 20):
            rows = []
            for doc, held, text in zip(batch.column("doc_id").to_pylist(), batch.column("held_out").to_pylist(), raw_texts(batch.column("text"))):
                words = words_of(text)
                number = np.fromiter(map(numbers.__getitem__, words), np.int64, len(words))
                missing = number < 0
                here = number[~missing]
                cls = np.where(missing, -1 - number, 0)
                cls[~missing] = model.class_of[here]
                logs = np.zeros(len(words))
                logs[~missing] = model.log_of[here]
                known = int(model.known[here].sum())
                rare = Counter([words[i] for i in np.flatnonzero(missing)])
                in_shape = cls >= first
                within = logs[in_shape].sum() - model.log_mass[cls[in_shape] - first].sum()
                rows.append((uid, doc, held, len(words) + 1, known + (model.end_count > 0), logs.sum() + log_end, within, int(missing.sum()), np.append(cls, 0).astype(np.uint16).tobytes(), list(rare), list(rare.values())))
                uid += 1
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), schema)], schema=schema)

    return docs.mapInArrow(run, "uid long, doc_id long, held_out boolean, n_tokens long, n_known long, counted double, within double, n_rare long, classes binary, rare array<binary>, rare_n array<int>")


def step_layout(seqs: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Sequences laid out by position: order of rows, active rows at each position, offsets, classes."""
    lengths = np.array([len(s) for s in seqs])
    order = by_length(lengths)
    sorted_len = lengths[order]
    top = int(sorted_len[0])
    active = len(seqs) - np.searchsorted(sorted_len[::-1], np.arange(top), side="right")
    offsets = np.concatenate(([0], np.cumsum(active)))
    flat = np.concatenate([seqs[i] for i in order])
    row = np.repeat(np.arange(len(seqs)), sorted_len)
    position = np.arange(len(flat)) - np.repeat(np.cumsum(sorted_len) - sorted_len, sorted_len)
    laid = np.empty(len(flat), np.int64)
    laid[offsets[position] + row] = flat
    return order, active, offsets, laid


class Hmm:
    """Start, transition and emission probabilities."""

    def __init__(self, start: np.ndarray, move: np.ndarray, emit: np.ndarray):
        self.start, self.move, self.emit = start, move, emit
        self.by_class = np.ascontiguousarray(emit.T)

    def forward(self, seqs: list[np.ndarray]) -> np.ndarray:
        """log10 likelihood of each whole sequence, by the scaled recursion."""
        order, active, offsets, laid = step_layout(seqs)
        out = np.zeros(len(seqs))
        b = self.by_class[laid]
        scale = np.empty(len(laid))
        a = self.start * b[: offsets[1]]
        for t in range(len(active)):
            n, at = active[t], offsets[t]
            if t:
                a = (a[:n] @ self.move) * b[at : at + n]
            s = a.sum(axis=1)
            scale[at : at + n] = s
            a /= s[:, None]
        logs = np.log10(scale)
        row = np.arange(len(laid)) - np.repeat(offsets[:-1], active)
        out[order] = np.bincount(row, weights=logs, minlength=len(seqs))
        return out

    def expect(self, seqs: list[np.ndarray], starts: np.ndarray) -> dict[str, np.ndarray]:
        """Expected counts of whole documents, given as runs in order; `starts` tells which runs begin one."""
        entering, behind = self.carried(seqs, starts)
        order, active, offsets, laid = step_layout(seqs)
        entering, inner = entering[order], ~starts[order]
        k = len(self.start)
        b = self.by_class[laid]
        alpha = np.empty_like(b)
        scale = np.empty(len(laid))
        a = np.where(inner[:, None], entering @ self.move, self.start) * b[: offsets[1]]
        for t in range(len(active)):
            n, at = active[t], offsets[t]
            if t:
                a = (a[:n] @ self.move) * b[at : at + n]
            s = a.sum(axis=1)
            a /= s[:, None]
            alpha[at : at + n], scale[at : at + n] = a, s
        last = offsets[np.array([len(seqs[i]) for i in order]) - 1] + np.arange(len(seqs))
        beta = behind[order]
        beta = beta / (alpha[last] * beta).sum(axis=1, keepdims=True)
        moved = np.zeros((k, k))
        gamma = alpha  # turned into posteriors from the end on
        for t in range(len(active) - 1, 0, -1):
            n, at, before = active[t], offsets[t], offsets[t - 1]
            ahead = beta[:n] * b[at : at + n] / scale[at : at + n, None]
            moved += alpha[before : before + n].T @ ahead
            gamma[at : at + n] *= beta[:n]
            beta[:n] = ahead @ self.move.T
        if inner.any():  # the step into a run from the one before it
            moved += entering[inner].T @ (beta * b[: len(seqs)] / scale[: len(seqs), None])[inner]
        gamma[: len(seqs)] *= beta
        size = self.emit.shape[1]
        emitted = np.stack([np.bincount(laid, weights=gamma[:, i], minlength=size) for i in range(k)])
        return {"start": gamma[: len(seqs)][starts[order]].sum(axis=0), "move": moved * self.move, "emit": emitted}

    def carried(self, seqs: list[np.ndarray], starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each run the forward message at the end of the run before it, and the backward message at its own end."""
        k = len(self.start)
        before, behind = np.zeros((len(seqs), k)), np.ones((len(seqs), k))
        later = np.flatnonzero(~starts)
        if not len(later):
            return before, behind
        heads = later[starts[later - 1]] - 1
        through = dict(zip(later.tolist(), self.transfer([seqs[i] for i in later], np.eye(k), False)))
        ends = dict(zip(heads.tolist(), self.transfer([seqs[i] for i in heads], self.start[None], True)[:, 0]))
        for i in later.tolist():
            v = ends[i - 1] if starts[i - 1] else before[i - 1] @ through[i - 1]
            before[i] = v / v.sum()
        for i in later[::-1].tolist():
            v = through[i] @ behind[i]
            behind[i - 1] = v / v.sum()
        return before, behind

    def transfer(self, seqs: list[np.ndarray], first: np.ndarray, begins: bool) -> np.ndarray:
        """Products of the steps through each sequence, up to a factor, from the rows of `first`."""
        order, active, offsets, laid = step_layout(seqs)
        rows, k = first.shape
        p = np.broadcast_to(first, (len(seqs), rows, k)).copy()
        for t in range(len(active)):
            n, at = active[t], offsets[t]
            moved = p[:n] if begins and not t else (p[:n].reshape(-1, k) @ self.move).reshape(n, rows, k)
            p[:n] = moved * self.by_class[laid[at : at + n]][:, None, :]
            p[:n] /= p[:n].max(axis=(1, 2), keepdims=True)
        out = np.empty_like(p)
        out[order] = p
        return out

    def updated(self, counts: dict[str, np.ndarray], smoothing: float) -> "Hmm":
        total = counts["emit"].sum(axis=0) + 0.1
        background = total / total.sum()
        emit = counts["emit"] + smoothing * background
        move = counts["move"] + 0.1
        start = counts["start"] + 0.1
        return Hmm(start / start.sum(), move / move.sum(axis=1, keepdims=True), emit / emit.sum(axis=1, keepdims=True))

    @classmethod
    def initial(cls, background: np.ndarray, states: int, seed: int) -> "Hmm":
        draw = np.random.default_rng(seed)
        emit = background * draw.gamma(1.0, 1.0, (states, len(background))) + 1e-12
        move = np.full((states, states), 0.1 / max(states - 1, 1)) + np.eye(states) * 0.9
        return cls(np.full(states, 1 / states), move / move.sum(axis=1, keepdims=True), emit / emit.sum(axis=1, keepdims=True))


def runs_of(blobs: list[bytes], length: int) -> tuple[list[np.ndarray], np.ndarray]:
    """Class sequences cut into runs, and which of them begin a document."""
    seqs, starts = [], []
    for blob in blobs:
        whole = np.frombuffer(blob, np.uint16)
        for at in range(0, len(whole), length):
            seqs.append(whole[at : at + length])
            starts.append(at == 0)
    return seqs, np.array(starts, bool)


def grouped(blobs: list[bytes], limit: int = 1 << 20):
    """Blobs in groups of about `limit` bytes, so that work arrays stay small."""
    group, held = [], 0
    for x in blobs:
        if group and held + len(x) > limit:
            yield group
            group, held = [], 0
        group.append(x)
        held += len(x)
    if group:
        yield group


def baum_welch_round(train: DataFrame, model: Hmm, settings: HmmSettings) -> Hmm:
    """One round over all training documents; partitions send expected counts, which are summed before the driver."""
    k, size = model.emit.shape
    sent = train.sparkSession.sparkContext.broadcast((model.start, model.move, model.emit))

    def run(batches):
        own = Hmm(*sent.value)
        total = np.zeros(k + k * k + k * size)
        seen = False
        for batch in batches:
            for group in grouped(batch.column("classes").to_pylist()):
                c = own.expect(*runs_of(group, settings.train_run))
                total += np.concatenate([c["start"], c["move"].ravel(), c["emit"].ravel()])
                seen = True
        if seen:
            at = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(total[at])], ["at", "n"])

    rows = train.select("classes").mapInArrow(run, "at int, n double").groupBy("at").agg(F.sum("n").alias("n")).toArrow()
    total = np.zeros(k + k * k + k * size)
    total[rows.column("at").to_numpy()] = rows.column("n").to_numpy()
    sent.unpersist()
    return model.updated({"start": total[:k], "move": total[k : k + k * k].reshape(k, k), "emit": total[k + k * k :].reshape(k, size)}, settings.smoothing)


def warm_start(train: DataFrame, size: int, settings: HmmSettings) -> Hmm:
    """A first model from at most `warm_documents` documents, picked by a hash of their row."""
    some = train.select("uid").orderBy(F.xxhash64("uid", F.lit(settings.seed)), "uid").limit(settings.warm_documents)
    picked = train.join(F.broadcast(some), "uid", "left_semi").select("uid", "classes").orderBy("uid").toArrow()
    blobs = picked.column("classes").to_pylist()
    background = np.full(size, 0.1)
    for blob in blobs:
        background += np.bincount(np.frombuffer(blob, np.uint16), minlength=size)
    model = Hmm.initial(background / background.sum(), settings.states, settings.seed)
    for _ in range(settings.warm_rounds if blobs else 0):
        parts = [model.expect(*runs_of(group, settings.train_run)) for group in grouped(blobs)]
        model = model.updated({k: sum(p[k] for p in parts) for k in parts[0]}, settings.smoothing)
    return model


def hmm_scores(docs: DataFrame, settings: HmmSettings = HmmSettings(), mod: int = 5, held: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Scores of all documents by a model that learns from those outside the held-out fold."""
    spark = docs.sparkSession
    rows = id_and_text(docs, id_col, text_col)
    rows = rows.withColumn("held_out", F.coalesce(fold(rows.doc_id, mod) == held, F.lit(True)))
    n_docs, n_train = rows.agg(F.count("*"), F.coalesce(F.sum((~F.col("held_out")).cast("long")), F.lit(0))).first()
    vocabulary = scratch.save(count_words(rows.where(~F.col("held_out"))), "words")
    train_words, distinct = vocabulary.agg(F.coalesce(F.sum("in_train"), F.lit(0)), F.count("*")).first()
    n, v = train_words + n_train, distinct + (n_train > 0)

    # Bounded by construction: at most `cached_words` words reach that share of the tokens.
    frequent = (F.col("in_train") * settings.cached_words >= train_words) & (F.octet_length("word") <= LONGEST_CACHED)
    listed = vocabulary.where(frequent).select("word", "in_train").toArrow()
    cached = dict(zip(listed.column("word").to_pylist(), listed.column("in_train").to_pylist()))
    own = sorted(w for w, c in cached.items() if c * settings.own_classes >= train_words)
    mass = class_mass(vocabulary, set(own), settings)
    classes = Classes(settings, own, cached, mass, n_train)
    encoded = scratch.save(encode(rows, spark.sparkContext.broadcast(classes)), "encoded")

    train = encoded.where(~F.col("held_out"))
    model = warm_start(train, classes.size, settings)
    for _ in range(settings.rounds if n_train else 0):
        model = baum_welch_round(train, model, settings)
    sent = spark.sparkContext.broadcast((model.start, model.move, model.emit))

    def score(batches):
        own_model = Hmm(*sent.value)
        for batch in batches:
            out = [own_model.forward([np.frombuffer(x, np.uint16) for x in g]) for g in grouped(batch.column("classes").to_pylist())]
            likelihood = np.concatenate(out) if out else np.zeros(0)
            yield pa.RecordBatch.from_arrays([batch.column(c) for c in ("uid", "doc_id", "held_out", "n_tokens", "n_known", "counted", "within", "n_rare")] + [pa.array(likelihood)], [*("uid", "doc_id", "held_out", "n_tokens", "n_known", "counted", "within", "n_rare"), "likelihood"])

    kept = ("uid", "doc_id", "held_out", "n_tokens", "n_known", "counted", "within", "n_rare", "classes")
    scored = encoded.select(*kept).mapInArrow(score, "uid long, doc_id long, held_out boolean, n_tokens long, n_known long, counted double, within double, n_rare long, likelihood double")

    counts = vocabulary.where(~frequent).select("word", "in_train")
    uses = encoded.where(F.col("n_rare") > 0).select("uid", F.explode(F.arrays_zip("rare", "rare_n")).alias("use")).select("uid", F.col("use.rare").alias("word"), F.col("use.rare_n").alias("times"))
    found = uses.join(counts, "word").groupBy("uid").agg(
        F.sum("times").alias("rare_known"),
        F.sum(F.col("times") * (F.log10(F.col("in_train") + 0.5) - LOG_HALF)).alias("rare_gain"),
    )
    log_all = float(np.log10(n + 0.5 * (v + 1)))
    rare = F.col("n_rare") * LOG_HALF + F.coalesce("rare_gain", F.lit(0.0))
    return scored.join(found, "uid", "left").select(
        "doc_id",
        "held_out",
        "n_tokens",
        (F.col("n_known") + F.coalesce("rare_known", F.lit(0))).alias("n_known"),
        F.lit(n).cast("long").alias("train_tokens"),
        (F.col("counted") + rare - F.col("n_tokens") * log_all).alias("base_score"),
        (F.col("likelihood") + F.col("within") + rare).alias("score"),
    )
