"""Language identification: averaged hashed subword vectors under a linear softmax.

A text is the mean of the vectors of its subwords (all byte 3- and 4-grams of its
lower-cased words, word ends included, hashed into ``BUCKETS`` rows), followed by
a linear layer and a softmax, trained by stochastic gradient descent in NumPy.
After training, vectors times layer collapse into one score per bucket and
language, so prediction is one gather and one mean over the whole text.

The fit uses a bounded sample, the documented parameter ``max_rows`` (and at most
``max_bytes`` of text): distinct pairs of text and language by hash order, so
copies take one place and the sample grows with the table until the bound, with
places for every language; a text that does not fit is passed over.  A fifth of
each language's sample is held back from the training to fit the temperature of the softmax and the rejection.

Beside the languages the softmax has one class for text of no learned language.
Its training texts are pieces of the others with their letters drawn anew, half of
them from the piece itself and half evenly from all letters, so the parts of words
that no language has speak for it.  A text is rejected if the log odds that it is
of any learned language lie below a threshold.  That threshold is calibrated
on the held-back fifth by length, as a short text says less: for pieces of 1, 3, 7,
15, ... bytes it lies half-way between what all but ``reject_share`` of the pieces
reach and what all but ``pass_share`` of their scrambled forms stay under; where the
two overlap the first decides, so clean short texts stay.

Edge cases: null texts and texts without a letter get ``und``, score 0 and are
rejected; null languages are not learned from; with no labelled row at all every
text is ``und``; one language is predicted with score 1.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from stalegrad.llm.common import fresh
from stalegrad.llm.kernels import U64, blocks

BUCKETS = 1 << 15
UNDETERMINED = "und"
NEGATIVE_BYTES = 1 << 10


def _folded(data: np.ndarray) -> np.ndarray:
    """Letters of A-Z lower-cased, every other ASCII byte that is no letter a space."""
    table = np.arange(256, dtype=np.uint8)
    table[:128] = 32
    table[97:123] = np.arange(97, 123)
    table[65:91] = np.arange(97, 123)
    return table[data]


def subwords(data: np.ndarray) -> np.ndarray:
    """Bucket of each byte 3-gram and 4-gram of one text, with a space at both ends."""
    text = np.concatenate(([32], _folded(data), [32])).astype(np.uint64)
    if len(text) < 4:
        text = np.concatenate((text, np.full(4 - len(text), 32, dtype=np.uint64)))
    three = text[:-2] | text[1:-1] << U64(8) | text[2:] << U64(16)
    four = three[:-1] | text[3:] << U64(24) | U64(1 << 40)
    keys = np.concatenate((three[three != U64(0x202020)], four[four != U64(0x202020 | 32 << 24 | 1 << 40)]))
    return ((keys * U64(0x9E3779B97F4A7C15)) >> U64(64 - 15)).astype(np.int64)


@dataclass
class Model:
    """``scores``: a row for each bucket, a column for each language and one for text of none; logits are scaled by ``sharpness``."""

    languages: list[str]
    scores: np.ndarray
    bias: np.ndarray
    sharpness: float = 1.0
    thresholds: tuple[float, ...] = ()  # by the power of two that the subwords reach; longer texts have the last one

    def logits(self, data: np.ndarray) -> np.ndarray:
        at = subwords(data)
        if not len(at):
            return self.bias.copy()
        counts = np.bincount(at, minlength=BUCKETS) if len(at) > BUCKETS else None
        total = counts @ self.scores if counts is not None else self.scores[at].sum(axis=0)
        return total / len(at) + self.bias

    def judge(self, data: np.ndarray) -> tuple[np.ndarray, float]:
        """The probability of each language if it is one of them, and the log odds that it is one of them."""
        z = self.logits(data) * self.sharpness
        top = z[:-1].max()
        p = np.exp(z[:-1] - top)
        return p / p.sum(), float(top + np.log(p.sum()) - z[-1])

    def probabilities(self, data: np.ndarray) -> np.ndarray:
        return self.judge(data)[0]

    def threshold(self, size: int) -> float:
        """What the log odds of being of a learned language must reach for a text of ``size`` bytes."""
        if not self.thresholds:
            return -np.inf
        return self.thresholds[min(max(1, size).bit_length(), len(self.thresholds)) - 1]


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(axis=1, keepdims=True))
    return e / e.sum(axis=1, keepdims=True)


def train(texts: list[bytes], labels: list[str], width: int = 16, epochs: int = 10, rate: float = 5.0, batch: int = 8, seed: int = 5, reject_share: float = 0.01, pass_share: float = 0.01) -> Model:
    """Stochastic gradient descent on the cross-entropy, then calibration on the held-back fifth."""
    languages = sorted(set(labels))
    if not languages:
        return Model([], np.zeros((BUCKETS, 1)), np.zeros(1))
    rng = np.random.default_rng(seed)
    none = len(languages)
    target = np.array([languages.index(x) for x in labels])
    data = [np.frombuffer(t, dtype=np.uint8) for t in texts]
    order = rng.permutation(len(texts))
    each = [order[target[order] == k] for k in range(none)]
    held = np.concatenate([rows[: len(rows) // 5] for rows in each])  # so that every language is trained on
    fit = np.concatenate([rows[len(rows) // 5 :] for rows in each])
    letters = _letters(data[i] for i in fit)
    if len(letters):  # one scrambled piece for every second text
        rest = [_scrambled(_piece(data[i], NEGATIVE_BYTES, rng), letters, rng) for i in fit[::2]]
        fit = np.concatenate((fit, np.arange(len(data), len(data) + len(rest))))
        data, target = data + rest, np.concatenate((target, np.full(len(rest), none)))
    features = []
    for own in data:
        at, n = np.unique(subwords(own), return_counts=True)
        features.append((at, n / max(1, n.sum())))
    vectors = rng.uniform(-1, 1, (BUCKETS, width)) / width
    layer, bias = np.zeros((width, none + 1)), np.zeros(none + 1)
    steps, done = max(1, epochs * -(-len(fit) // batch)), 0
    for _ in range(epochs):
        fit = rng.permutation(fit)
        for lo in range(0, len(fit), batch):
            rows = fit[lo : lo + batch]
            step = rate * (1 - done / steps)
            done += 1
            hidden = np.stack([w @ vectors[at] for at, w in (features[i] for i in rows)])
            error = _softmax(hidden @ layer + bias)
            error[np.arange(len(rows)), target[rows]] -= 1
            error /= len(rows)
            back = error @ layer.T
            layer -= step * hidden.T @ error
            bias -= step * error.sum(axis=0)
            for k, i in enumerate(rows):
                at, w = features[i]
                vectors[at] -= step * len(rows) * w[:, None] * back[k]
    model = Model(languages, vectors @ layer, bias)
    check = held if len(held) else order
    logits = np.stack([w @ model.scores[at] + bias for at, w in (features[i] for i in check)])
    grid = np.exp(np.linspace(np.log(0.25), np.log(16), 40))
    rows, doubt = np.arange(len(check)), 1 / (len(check) + 2)  # no finite check makes a text certain
    loss = []
    for g in grid:
        p = np.maximum(_softmax(logits * g), 1e-12)
        loss.append(-((1 - doubt) * np.log(p[rows, target[check]]) + doubt * np.log(p).mean(axis=1)).mean())
    model.sharpness = float(grid[int(np.argmin(loss))])
    if len(letters):
        model.thresholds = _thresholds(model, [data[i] for i in check], letters, rng, reject_share, pass_share)
    return model


def _letters(texts) -> np.ndarray:
    """The bytes that stand inside words, each once."""
    seen = np.zeros(256, dtype=bool)
    for t in texts:
        seen[_folded(t)] = True
    seen[32] = False
    return np.flatnonzero(seen).astype(np.uint8)


def _piece(text: np.ndarray, size: int, rng: np.random.Generator) -> np.ndarray:
    at = int(rng.integers(0, max(1, len(text) - size + 1)))
    return text[at : at + size]


def _scrambled(piece: np.ndarray, letters: np.ndarray, rng: np.random.Generator) -> np.ndarray:
    """The piece with its letters (and bytes above ASCII) shuffled, or drawn evenly from ``letters``."""
    out = _folded(piece)
    inside = np.flatnonzero(out != 32)
    out[inside] = rng.permutation(out[inside]) if rng.random() < 0.5 else rng.choice(letters, len(inside))
    return out


def _thresholds(model: Model, held: list[np.ndarray], letters: np.ndarray, rng: np.random.Generator, reject_share: float, pass_share: float) -> tuple[float, ...]:
    """By power of two of the size: what held-back pieces reach and scrambled ones do not."""
    out: list[float] = []
    for power in range(1, 1 + max(map(len, held), default=0).bit_length()):
        size = (1 << power) - 1
        long_enough = [t for t in held if len(t) >= size]
        if not long_enough:
            break
        known, foreign = [], []
        for i in range(max(50, min(400, (1 << 21) // size))):
            piece = _piece(long_enough[i % len(long_enough)], size, rng)
            known.append(model.judge(piece)[1])
            foreign.append(model.judge(_scrambled(piece, letters, rng))[1])
        least, most = float(np.quantile(known, reject_share)), float(np.quantile(foreign, 1 - pass_share))
        out.append((least + most) / 2 if most < least else least)
    return tuple(out)


def _chosen(keys: list, max_rows: int, max_bytes: int) -> list:
    """The rows of ``keys`` that fit, in order; texts above a sixteenth of the room wait until the others are in."""
    room, taken = max_bytes, []
    for late in (False, True):
        for r in keys:
            if (r["_n"] > max_bytes // 16) == late and r["_n"] <= room and len(taken) < max_rows:
                room -= r["_n"]
                taken.append(r)
    return taken


def sample(docs: DataFrame, max_rows: int, max_bytes: int) -> list[tuple[str, str]]:
    """At most ``max_rows`` distinct (text, lang): half the places are dealt evenly over the languages, the rest by hash order.

    The number of distinct texts of a language gives a hash below which four times
    ``max_rows`` of them are expected, so what is ranked does not grow with the table.
    """
    key = F.shiftrightunsigned(F.xxhash64("text", "lang"), 1).alias("_at")
    labelled = docs.where("lang IS NOT NULL AND text IS NOT NULL").select("text", "lang", key, F.octet_length("text").alias("_n")).where(F.col("_n") <= max_bytes)
    # a sample has no room for more languages than rows: the largest ones
    sizes = labelled.groupBy("lang").agg(F.approx_count_distinct("_at").alias("_size")).orderBy(F.desc("_size"), "lang").limit(max_rows).collect()
    if not sizes:
        return []
    shares = [(r["lang"], min(1.0, 4 * max_rows / max(1, r["_size"]))) for r in sizes]
    cut = F.broadcast(docs.sparkSession.createDataFrame(shares, "lang string, _share double"))
    near = labelled.select("lang", "_at", "_n").join(cut, "lang").where(F.col("_at") <= F.col("_share") * float(1 << 63))
    distinct = near.groupBy("lang", "_at").agg(F.min("_n").alias("_n"))
    ranks = distinct.withColumn("_rank", F.row_number().over(Window.partitionBy("lang").orderBy("_at")))
    turn = F.least("_rank", F.lit(max(1, max_rows // (2 * len(sizes))) + 1))
    keys = ranks.withColumn("_turn", turn).orderBy("_turn", "_at", "lang").limit(4 * max_rows).collect()
    wanted = {(r["_at"], r["lang"]) for r in _chosen(keys, max_rows, max_bytes)}
    rows = labelled.where(F.col("_at").isin([at for at, _ in wanted])).select("_at", "lang", "text").distinct().collect()
    texts = {(r["_at"], r["lang"]): r["text"] for r in sorted(rows, reverse=True)}  # the least of equal hashes
    return [(texts[k], k[1]) for k in sorted(wanted)]


def fit(docs: DataFrame, max_rows: int = 2_000, max_bytes: int = 16 << 20) -> Model:
    """A model from a bounded sample of the distinct labelled texts of ``docs`` (text, lang)."""
    rows = sample(docs, max_rows, max_bytes)
    return train([text.encode() for text, _ in rows], [lang for _, lang in rows])


def predict(docs: DataFrame, model: Model, carry: list[str], out: tuple[str, str, str] = ("lang_pred", "score", "rejected")) -> DataFrame:
    """The columns of ``carry`` with prediction, score and rejection, named by ``out``; only the text decides."""
    names = [f"_k{i}" for i in range(len(carry))]
    picked = docs.select(*[F.col(c).alias(k) for c, k in zip(carry, names, strict=True)], F.col("text").alias("_text"), F.coalesce(F.col("text").rlike(r"\p{L}"), F.lit(False)).alias("_letters"))
    shared = docs.sparkSession.sparkContext.broadcast(model)  # BUCKETS rows, whatever the table's size

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in batches:
            letters = batch.column("_letters").to_pylist()
            langs, scores, rejected = [], [], []
            for lo, hi, data, offs in blocks(batch.column("_text")):
                for r in range(hi - lo):
                    if not letters[lo + r] or not model.languages:
                        langs.append(UNDETERMINED)
                        scores.append(0.0)
                        rejected.append(True)
                        continue
                    own = data[offs[r] : offs[r + 1]]
                    p, known = model.judge(own)
                    k = int(p.argmax())
                    langs.append(model.languages[k])
                    scores.append(float(p[k]))
                    rejected.append(known < model.threshold(len(own)))
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(names)], pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array(rejected, pa.bool_())], names=[*names, "lang_pred", "score", "rejected"])

    fields = ", ".join([*(f"{k} {t}" for k, (_, t) in zip(names, picked.dtypes, strict=False)), "lang_pred string", "score double", "rejected boolean"])
    return picked.mapInArrow(read, fields).toDF(*carry, *out)


def learnable(docs: DataFrame) -> DataFrame:
    """Rows outside the held-out fold: crc32 of the id as text is not 0 modulo 5."""
    return docs.where(~_held_out())


def _held_out():
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(False))


def identify(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score, rejected for every row."""
    model = fit(learnable(docs))
    picked = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").withColumn("held_out", _held_out())
    return predict(picked, model, ["doc_id", "held_out"])


def keep_identified(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` whose language is not rejected; columns as they were."""
    model = fit(learnable(docs))
    own = tuple(fresh(docs, name) for name in ("lang_pred", "score", "rejected"))
    return predict(docs, model, docs.columns, own).where(~F.col(own[2])).select(*docs.columns)
