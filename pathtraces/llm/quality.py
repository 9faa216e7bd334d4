"""Quality rules: repetition counts, and divergence of a text's histograms from those of the languages.

Two histograms describe a text: its characters by class, and its words over a list of common function words (one more bin
holds all other words). Reference histograms are the sums over all texts of a language that pass the base rules. A text is
rejected when even its nearest reference is farther than a threshold in Jensen-Shannon distance (base 2, so 0 to 1); that of
words falls with their number. Texts too short for a stable histogram are not judged by it.

Nulls, empty texts: a null text has no words, like an empty one; both fail the base rules (fewer than ten words). Texts of
a null language are judged but add to no reference. Without any reference (empty table) the divergence is 0.
Repeated rows are judged each. Columns beside id, text and language are ignored by ``quality_scores`` and passed through
unread by ``quality_filter``.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathtraces.llm.common import parts, rolling, texts, word_hashes

# Frequent function words of four languages.
COMMON_WORDS = """
the of and to in a is that for it as was with be by on not he i this are or his from at which but have an had they you
were their one all we can her has there been if more when will would who so no
der die und den von zu das mit sich des auf für ist im dem nicht ein eine als auch es werden aus er hat dass sie nach wird
bei einer um am sind noch wie einem über einen so zum war haben nur oder aber vor zur bis mehr durch man sein wurde sei
de la le et les des en un du une que est pour qui dans par sur au plus pas ce il sont avec se ou son cette mais comme
on tout nous sa aux ces elle leur deux
el que y los se las del por con no una su para al lo como más o pero sus le ha me si sin sobre este ya entre cuando
todo esta ser son dos también fue había era muy
""".split()  # fmt: skip

#: Character classes, by the byte that begins the character; continuation bytes belong to none.
CLASSES = ("lower", "upper", "digit", "space", "stop", "symbol", "punctuation", "control", "beyond ascii")
SYMBOLS = b"#*$%&|<>"
MIN_WORDS, MIN_REPEAT, WINDOW = 10, 20, 5
#: Few words are far from any reference by chance, in proportion to the root of their number: the limit of words is WORD_LIMIT + WORD_SPREAD / sqrt(words).
CHAR_LIMIT, WORD_LIMIT, WORD_SPREAD = 0.33, 0.25, 1.3
CHAR_GUARD, WORD_GUARD = 200, 50


def _class_table() -> np.ndarray:
    at = np.full(256, 6, np.uint8)
    at[:32], at[127] = 7, 7
    at[97:123], at[65:91], at[48:58] = 0, 1, 2
    at[[32, *range(9, 14)]] = 3
    at[list(b".,;:!?'\"()-")] = 4
    at[list(SYMBOLS)] = 5
    at[0x80:0xC0] = 9
    at[0xC0:] = 8
    return at


_CLASS = _class_table()
_COMMON = {w.encode(): k + 1 for k, w in enumerate(dict.fromkeys(COMMON_WORDS))}
_BREAKS = bytes(32 if chr(c) in ".,;:!?'\"()-[]#*$%&|<>/\n\r\t\v\f" else c for c in range(256))
N_BINS = len(_COMMON) + 1


def base_counts(text: bytes) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    words = text.split()
    n = len(words)
    word_bytes = sum(map(len, words))
    word_chars = word_bytes if text.isascii() else sum(len(w.decode("utf-8", "replace")) for w in words)
    symbols = len(text) - len(text.translate(None, SYMBOLS))
    seen: set[bytes] = set()
    dup = 0
    for line in text.split(b"\n"):
        if line.split(None, 1):
            dup += line in seen
            seen.add(line)
    repeated = 0
    if n > WINDOW:
        runs = rolling(word_hashes(words), WINDOW)
        order = np.argsort(runs, kind="stable")
        sorted_runs = runs[order]
        same = sorted_runs[1:] == sorted_runs[:-1]
        if same.any():
            twice = np.zeros(len(runs), bool)
            twice[order[1:][same]] = True
            twice[order[:-1][same]] = True
            covers = np.zeros(n + 1, np.int64)
            np.add.at(covers, np.flatnonzero(twice), 1)
            np.add.at(covers, np.flatnonzero(twice) + WINDOW, -1)
            repeated = int((np.cumsum(covers[:n]) > 0).sum())
    return n, word_chars, symbols, dup, repeated


def base_failed(n_words: int, n_repeat_words: int) -> bool:
    return n_words < MIN_WORDS or 100 * n_repeat_words > MIN_REPEAT * n_words


def histograms(text: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Counts by character class, counts by common word (bin 0: every other word)."""
    classes = np.bincount(_CLASS[np.frombuffer(text, np.uint8)], minlength=10)[:9]
    words = text.lower().translate(_BREAKS).split()
    get = _COMMON.get
    return classes, np.bincount(np.fromiter((get(w, 0) for w in words), np.int64, len(words)), minlength=N_BINS)


def jensen_shannon(counts: np.ndarray, references: np.ndarray) -> float:
    """Distance of a histogram from the nearest row of ``references``."""
    if not len(references) or not counts.sum():
        return 0.0
    p = counts / counts.sum()
    q = references / references.sum(axis=1, keepdims=True)
    m = (p + q) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        left = np.where(p > 0, p * np.log2(p / m), 0).sum(axis=1)
        right = np.where(q > 0, q * np.log2(q / m), 0).sum(axis=1)
    return float(np.sqrt(np.clip((left + right) / 2, 0, 1)).min())


def _reference_rows(batches):
    """Sums over one task, a row for each language; the exchange gets these only."""
    import pyarrow as pa

    sums: dict[str, np.ndarray] = {}
    for batch in batches:
        for piece in parts(batch):
            for lang, text in zip(piece.column(1).to_pylist(), texts(piece.column(0)), strict=True):
                n, *_, repeated = base_counts(text or b"")
                if lang is None or base_failed(n, repeated):
                    continue
                both = np.concatenate(histograms(text))
                if lang in sums:
                    sums[lang] += both
                else:
                    sums[lang] = both.astype(np.int64)
    rows = [(lang, k, int(v)) for lang, s in sums.items() for k, v in enumerate(s) if v]
    yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.int64())], ["lang", "bin", "n"])


def language_references(docs: DataFrame, text: str = "text", lang: str = "lang") -> dict[str, np.ndarray]:
    """language -> counts (character classes, then common words), over all texts that pass the base rules. One row for each
    language and bin reaches the driver."""
    sums = docs.select(F.col(text).alias("t"), F.col(lang).alias("l")).mapInArrow(_reference_rows, "lang string, bin int, n long")
    out: dict[str, np.ndarray] = {}
    for row in sums.groupBy("lang", "bin").agg(F.sum("n").alias("n")).collect():
        out.setdefault(row.lang, np.zeros(9 + N_BINS))[row.bin] = row.n
    return out


class Judge:
    """Verdicts against given references."""

    def __init__(self, references: dict[str, np.ndarray], char_limit: float = CHAR_LIMIT, word_limit: float = WORD_LIMIT, char_guard: int = CHAR_GUARD, word_guard: int = WORD_GUARD, word_spread: float = WORD_SPREAD):
        stacked = np.array([references[k] for k in sorted(references)]).reshape(-1, 9 + N_BINS)
        self.chars = stacked[:, :9][stacked[:, :9].sum(axis=1) > 0]
        self.words = stacked[:, 9:][stacked[:, 9:].sum(axis=1) > 0]
        self.char_limit, self.word_limit, self.char_guard, self.word_guard, self.word_spread = char_limit, word_limit, char_guard, word_guard, word_spread

    def __call__(self, text: bytes) -> tuple:
        """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, char_distance, word_distance, kept."""
        counts = base_counts(text)
        failed = base_failed(counts[0], counts[4])
        classes, words = histograms(text)
        char = jensen_shannon(classes, self.chars) if classes.sum() >= self.char_guard else 0.0
        n = int(words.sum())
        word = jensen_shannon(words, self.words) if n >= self.word_guard else 0.0
        limit = self.word_limit + self.word_spread / max(n, 1) ** 0.5
        return (*counts, failed, char, word, not failed and char <= self.char_limit and word <= limit)


def quality_scores(docs: DataFrame, id: str = "doc_id", text: str = "text", lang: str = "lang", references=None, **limits) -> DataFrame:
    """Per row: the id, the base counts, both distances and the verdict."""
    judge = Judge(language_references(docs, text, lang) if references is None else references, **limits)

    def run(batches):
        import pyarrow as pa

        kinds = [pa.int64()] * 5 + [pa.bool_(), pa.float64(), pa.float64(), pa.bool_()]
        for batch in batches:
            for piece in parts(batch):
                found = list(zip(*[judge(t or b"") for t in texts(piece.column(1))], strict=True))
                yield pa.RecordBatch.from_arrays([piece.column(0), *(pa.array(c, k) for c, k in zip(found, kinds, strict=True))], names)

    names = ["id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "char_distance", "word_distance", "kept"]
    kind = dict(docs.dtypes)[id]
    schema = f"id {kind}, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, char_distance double, word_distance double, kept boolean"
    return docs.select(F.col(id).alias("id"), F.col(text).alias("text")).mapInArrow(run, schema).withColumnRenamed("id", id)


def quality_filter(docs: DataFrame, text: str = "text", lang: str = "lang", references=None, **limits) -> DataFrame:
    """The rows that are kept, with all their columns."""
    judge = Judge(language_references(docs, text, lang) if references is None else references, **limits)
    at = docs.columns.index(text)

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for piece in parts(batch):
                yield piece.filter(pa.array([judge(t or b"")[-1] for t in texts(piece.column(at))], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
