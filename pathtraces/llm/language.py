"""Language by compression: a text belongs to the language whose dictionary compresses it best.

Texts are brought to lower-case words first: whatever is no letter becomes one space. Each language has a raw-content zstandard
dictionary: training texts, one after the other, from a bounded sample in the order of a hash (``PER_LANGUAGE`` distinct texts, of
longer ones the first ``TEXT_BYTES``, together ``DICTIONARY_BYTES``). A text is compressed once with each, all at one level;
the smallest result wins. The frames' fixed costs are taken off by compressing nothing with the same settings. A text that
saves too little against the runner-up is marked ``rejected``: its prediction stands, with a low score. The score is the share
the winner gets when every saved byte per kilobyte counts as evidence, from 0 to 1.

A text that is null, empty or holds no letter gets ``und`` and score 0. Ties go to the language with more training texts, then the first by code point. Very long
texts are compressed whole. With an empty training set every text gets ``und``. Repeated rows are judged each; columns
beside id and text are ignored."""

from __future__ import annotations

import numpy as np
import regex
import zstandard
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathtraces.llm.common import parts, spill

PER_LANGUAGE, TEXT_BYTES, DICTIONARY_BYTES, LEVEL = 600, 16_000, 112_000, 6
MARGIN, SHARPNESS = 0.02, 60.0
_OTHER = regex.compile(r"\P{L}+")


def plain(text: str) -> str:
    """Lower-case words, with one space before and after each."""
    return _OTHER.sub(" ", f" {text.lower()} ")


def sampled(docs: DataFrame, text: str, lang: str, per_language: int = PER_LANGUAGE, text_bytes: int = TEXT_BYTES) -> dict[str, tuple[int, list[str]]]:
    """How many training texts each language has, and of its distinct ones the first ``per_language`` in the order of their hash, each its beginning of at most
    ``text_bytes``. Distinct hashes are counted by language and leading bits; only the bins that the first ``per_language`` reach into are sorted."""
    rows = docs.where(F.col(lang).isNotNull() & (F.octet_length(text) > 0)).select(F.col(lang).alias("lang"), F.col(text).alias("text"), F.xxhash64(text).alias("h"))
    hashes = spill(rows.groupBy("lang", "h").agg(F.count(F.lit(1)).alias("n")), "language-hashes").withColumn("bin", F.shiftright("h", 52))
    bins = hashes.groupBy("lang", "bin").agg(F.count(F.lit(1)).alias("texts"), F.sum("n").alias("n"))
    before = F.sum("texts").over(Window.partitionBy("lang").orderBy("bin")) - F.col("texts")
    near = hashes.join(F.broadcast(bins.withColumn("before", before).where(F.col("before") < per_language).select("lang", "bin")), ["lang", "bin"])
    first = near.groupBy("lang").agg(F.slice(F.array_sort(F.collect_list("h")), 1, per_language).alias("h")).select("lang", F.explode("h").alias("h"))
    best = rows.join(F.broadcast(first), ["lang", "h"]).groupBy("lang", "h").agg(F.min(F.substring(F.encode("text", "utf-8"), 1, text_bytes)).alias("text"))
    out: dict[str, tuple[int, list[str]]] = {r.lang: (r.n, []) for r in bins.groupBy("lang").agg(F.sum("n").alias("n")).collect()}
    for r in sorted(best.collect(), key=lambda r: r.h):
        out[r.lang][1].append(bytes(r.text).decode(errors="ignore"))
    return out


class Compressors:
    """The languages' dictionaries, ready to judge texts."""

    def __init__(self, samples: dict[str, tuple[int, list[str]]], size: int = DICTIONARY_BYTES, level: int = LEVEL):
        self.langs = sorted(samples, key=lambda k: (-samples[k][0], k))
        self.content = {k: "".join(map(plain, samples[k][1])).encode()[-size:] for k in self.langs}
        self.level = level
        self._ready: list | None = None

    def __getstate__(self):
        return {"langs": self.langs, "content": self.content, "level": self.level, "_ready": None}

    def ready(self) -> list:
        if self._ready is None:
            self._ready = []
            for lang in self.langs:
                data = zstandard.ZstdCompressionDict(self.content[lang], dict_type=zstandard.DICT_TYPE_RAWCONTENT)
                data.precompute_compress(level=self.level)
                self._ready.append(zstandard.ZstdCompressor(dict_data=data, write_checksum=False, write_content_size=False, write_dict_id=False))
            self.fixed = len(self._ready[0].compress(b"")) if self.langs else 0
        return self._ready

    def judge(self, text: str | None) -> tuple[str, float, bool]:
        """Language, score, whether the margin is too narrow to trust it."""
        ready = self.ready()
        raw = plain(text or "").encode()
        if not ready or not raw.strip():
            return "und", 0.0, True
        sizes = np.array([len(c.compress(raw)) for c in ready], float) - self.fixed
        best = int(sizes.argmin())
        gaps = (sizes - sizes[best]) / max(1.0, sizes.max())
        evidence = np.exp(-SHARPNESS * gaps)
        runner = float(np.partition(gaps, 1)[1]) if len(gaps) > 1 else 1.0
        return self.langs[best], float(1 / evidence.sum()), runner < MARGIN


def train(docs: DataFrame, where: Column, text: str = "text", lang: str = "lang", per_language: int = PER_LANGUAGE) -> Compressors:
    return Compressors(sampled(docs.where(where), text, lang, per_language))


def languages(docs: DataFrame, model: Compressors, id: str = "doc_id", text: str = "text") -> DataFrame:
    """Per row: ``id``, ``lang_pred``, ``score``, ``rejected``."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for piece in parts(batch):
                found = list(zip(*map(model.judge, piece.column(1).to_pylist()), strict=True))
                yield pa.RecordBatch.from_arrays([piece.column(0), *(pa.array(c, k) for c, k in zip(found, (pa.string(), pa.float64(), pa.bool_()), strict=True))], ["id", "lang_pred", "score", "rejected"])

    schema = f"id {dict(docs.dtypes)[id]}, lang_pred string, score double, rejected boolean"
    return docs.select(F.col(id).alias("id"), F.col(text).alias("text")).mapInArrow(run, schema).withColumnRenamed("id", id)
