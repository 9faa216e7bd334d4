"""Toxicity by a factorization machine over hashed terms.

A text's terms are its words (lower case, cut at punctuation) and the first four and five letters of longer words, each hashed to
one of 2**22 slots, present or not. The machine adds a weight for each term and, for each pair of terms, the inner
product of their factors, so a word can count for more beside another than alone.

It learns from a sample of labelled texts of about ``TRAIN_ROWS`` (all of them if there are fewer), those whose id's hash is small. The
sample is drawn from the labels alone, so it is small enough to be sent to the texts, which stay where they are.
Slots take part if their presence goes with the label (likelihood ratio) or they are among the most frequent, which serve as
context; ``SLOTS`` at most. Training runs on the driver over the sample's slot numbers only.

Null and empty texts have no terms and get the score of the bias. Texts are read whole. Labels that are null don't count; with one class
or none, every score is that share. Repeated rows are scored each; columns beside id and text are ignored."""

from __future__ import annotations

import numpy as np
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathtraces.llm.common import parts, spill, texts

BITS, TRAIN_ROWS, SLOTS, CONTEXT, FACTORS = 22, 40_000, 6000, 300, 4
EPOCHS, BATCH, RATE, DECAY, SEED, THRESHOLD = 12, 256, 0.08, 2e-6, 7, 0.7
_BREAKS = bytes(c if chr(c).isalnum() or c >= 0x80 else 32 for c in range(256))


def word_slots(word: bytes) -> tuple[int, ...]:
    """The slots of a word and of its beginnings."""
    terms = [word]
    letters = word.decode("utf-8", "replace")
    terms += [b"^" + letters[:k].encode() for k in (4, 5) if len(letters) > k]
    return tuple(xxhash.xxh64_intdigest(t, 3) >> (64 - BITS) for t in terms)


class _Slots(dict):
    """word -> its slots (as numbers within a model, where there is one)."""

    LIMIT = 250_000

    def __init__(self, number: dict[int, int] | None = None):
        super().__init__()
        self.number = number

    def __missing__(self, word: bytes):
        if len(self) > self.LIMIT:
            self.clear()
        found = word_slots(word)
        if self.number is not None:
            found = tuple(self.number[s] for s in found if s in self.number)
        self[word] = found
        return found


def text_slots(text: bytes, slots: _Slots) -> list[int]:
    """Distinct slots, ascending."""
    out: set[int] = set()
    for w in set(text.decode("utf-8", "replace").lower().encode().translate(_BREAKS).split()):
        out.update(slots[w])
    return sorted(out)


def slot_rows(docs: DataFrame, text: str = "text", label: str = "label") -> DataFrame:
    """``label``, ``slots``."""

    def run(batches):
        import pyarrow as pa

        slots = _Slots()
        for batch in batches:
            for piece in parts(batch):
                yield pa.RecordBatch.from_arrays([piece.column(1), pa.array([text_slots(t or b"", slots) for t in texts(piece.column(0))], pa.list_(pa.int32()))], ["label", "slots"])

    return docs.select(F.col(text).alias("text"), F.col(label).cast("int").alias("label")).mapInArrow(run, "label int, slots array<int>")


def chosen_slots(rows: DataFrame, n_pos: int, n_neg: int, slots: int = SLOTS, context: int = CONTEXT) -> list[int]:
    """By likelihood ratio among those in five texts or more, and the most frequent."""
    by_slot = rows.select("label", F.explode("slots").alias("slot")).groupBy("slot").agg(F.sum("label").alias("p"), F.sum(1 - F.col("label")).alias("q")).where("p + q >= 5")

    def part(seen: Column, total: int, share: Column) -> Column:
        return F.when(seen > 0, seen * F.log(seen / (share * total))).otherwise(0.0)

    share = (F.col("p") + F.col("q")) / F.lit(float(n_pos + n_neg))
    ratio = 2 * (part(F.col("p"), n_pos, share) + part(F.col("q"), n_neg, share) + part(n_pos - F.col("p"), n_pos, 1 - share) + part(n_neg - F.col("q"), n_neg, 1 - share))
    scored = spill(by_slot.withColumn("ratio", ratio).withColumn("n", F.col("p") + F.col("q")), "slots")
    telling = scored.where("ratio > 15").orderBy(F.desc("ratio"), "slot").limit(slots - context).collect()
    frequent = scored.orderBy(F.desc("n"), "slot").limit(context).collect()
    return sorted({r.slot for r in telling} | {r.slot for r in frequent})


class FactorizationMachine:
    def __init__(self, n: int, factors: int = FACTORS, seed: int = SEED):
        rng = np.random.default_rng(seed)
        self.bias, self.w, self.v = 0.0, np.zeros(n), rng.normal(0, 0.01, (n, factors))

    def raw(self, ids: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Scores of rows; row k has the slot numbers ``ids[ends[k-1]:ends[k]]``."""
        sums = np.concatenate([np.zeros((1, 2 * self.v.shape[1] + 1)), np.cumsum(np.column_stack([self.w[ids], self.v[ids], self.v[ids] ** 2]), axis=0)])
        each = sums[ends] - sums[np.concatenate([[0], ends[:-1]])]
        k = self.v.shape[1]
        return self.bias + each[:, 0] + 0.5 * (each[:, 1 : k + 1] ** 2 - each[:, k + 1 :]).sum(axis=1)

    def scores(self, ids: np.ndarray, ends: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.raw(ids, ends), -35, 35)))

    def fit(self, rows: list[np.ndarray], labels: np.ndarray, epochs: int = EPOCHS, seed: int = SEED) -> FactorizationMachine:
        rng = np.random.default_rng(seed)
        share = float(np.clip(labels.mean() if len(labels) else 0.0, 1e-6, 1 - 1e-6))
        self.bias = float(np.log(share / (1 - share)))
        if labels.min(initial=1) == labels.max(initial=0):
            return self
        gw, gv, gb = np.full_like(self.w, 1e-2), np.full_like(self.v, 1e-2), 1e-2
        sizes = np.array([len(r) for r in rows])
        for _ in range(epochs):
            order = rng.permutation(len(rows))
            for at in range(0, len(order), BATCH):
                few = order[at : at + BATCH]
                ids, ends = np.concatenate([rows[k] for k in few]), np.cumsum(sizes[few])
                off = self.scores(ids, ends) - labels[few]
                row = np.repeat(np.arange(len(few)), sizes[few])
                totals = np.zeros((len(few), self.v.shape[1]))
                np.add.at(totals, row, self.v[ids])
                each, per_id = np.unique(ids, return_inverse=True)
                dw = np.bincount(per_id, off[row], len(each)) / len(few) + DECAY * self.w[each]
                dv = np.zeros((len(each), self.v.shape[1]))
                np.add.at(dv, per_id, off[row, None] * (totals[row] - self.v[ids]))
                dv = dv / len(few) + DECAY * self.v[each]
                gw[each] += dw**2
                gv[each] += dv**2
                self.w[each] -= RATE * dw / np.sqrt(gw[each])
                self.v[each] -= RATE * dv / np.sqrt(gv[each])
                db = off.mean()
                gb += db**2
                self.bias -= RATE * db / np.sqrt(gb)
        return self


class ToxicityModel:
    def __init__(self, slots: list[int], machine: FactorizationMachine):
        self.number = {s: k for k, s in enumerate(slots)}
        self.machine = machine
        self._known: _Slots | None = None

    def __getstate__(self):
        return {"number": self.number, "machine": self.machine, "_known": None}

    def scores(self, batch: list[bytes | None]) -> np.ndarray:
        if self._known is None:
            self._known = _Slots(self.number)
        rows = [text_slots(t, self._known) if t else [] for t in batch]
        return self.machine.scores(np.array([k for r in rows for k in r], np.int64), np.cumsum([len(r) for r in rows]))


def train(docs: DataFrame, labels: DataFrame, id: str = "doc_id", text: str = "text", label: str = "label", train_rows: int = TRAIN_ROWS) -> ToxicityModel:
    """``docs``: ids and texts; ``labels``: ids and labels (0 or 1)."""
    labelled = labels.where(F.col(label).isin(0, 1)).select(F.col(id).alias("__id"), F.col(label).alias("label"))
    n = labelled.count()
    draw = F.shiftrightunsigned(F.xxhash64("__id"), 11) / F.lit(float(1 << 53))
    few = labelled.where(draw < train_rows / max(n, 1)) if n > train_rows else labelled
    rows = docs.select(F.col(id), F.col(text).alias("text")).join(F.broadcast(few), F.col(id) == F.col("__id"))
    rows = spill(slot_rows(rows.select("text", "label")), "slot-rows")
    n_pos, n_all = rows.agg(F.coalesce(F.sum("label"), F.lit(0)), F.count(F.lit(1))).first()
    if not n_all:
        return ToxicityModel([], FactorizationMachine(0).fit([], np.zeros(0)))
    slots = chosen_slots(rows, n_pos, n_all - n_pos)
    wanted = rows.sparkSession.createDataFrame([(slots,)], "wanted array<int>")
    kept = rows.join(F.broadcast(wanted)).select("label", F.array_intersect("slots", "wanted").alias("slots")).toArrow()
    pairs = sorted(zip(kept["label"].to_pylist(), map(sorted, kept["slots"].to_pylist()), strict=True))  # the same in every run
    found = np.array(slots, np.int64)
    cut = [np.searchsorted(found, np.array(x, np.int64)) for _, x in pairs]
    return ToxicityModel(slots, FactorizationMachine(len(slots)).fit(cut, np.array([y for y, _ in pairs], float)))


def toxicity(docs: DataFrame, model: ToxicityModel, id: str = "doc_id", text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """Per row: ``id``, ``score``, ``predicted``."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for piece in parts(batch):
                found = model.scores(texts(piece.column(1)))
                yield pa.RecordBatch.from_arrays([piece.column(0), pa.array(found, pa.float64()), pa.array((found >= threshold).astype(np.int32))], ["id", "score", "predicted"])

    return docs.select(F.col(id).alias("id"), F.col(text).alias("text")).mapInArrow(run, f"id {dict(docs.dtypes)[id]}, score double, predicted int").withColumnRenamed("id", id)
