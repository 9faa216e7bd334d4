"""Removal of passages that other documents hold, by repeated-phrase automata.

A window is ``width`` consecutive words. A word goes if a window that covers it also starts in a document of a smaller id.

1. Every text is marked by content: of the phrases of ``PHRASE`` words inside a window, the one of the smallest hash is the
   window's mark. Equal windows have equal marks, and about one phrase in twenty is a mark. Marks met in texts that differ are
   candidates. Equal texts need no more than their smallest id: all words of the others go.
2. Windows of candidate marks are counted by hash, with the smallest and largest id each: those with two are confirmed as recurring.
   Hashes only say what is worth looking for. The words of a confirmed window are taken from its first document.
3. Documents are dealt into blocks of about ``BLOCK_BYTES`` by a hash of their id, and each block gets the confirmed windows that recur in
   it, each once, however many of its documents hold it. There their marks' phrases are compiled to Aho-Corasick automata over words, one symbol a word, in shards of about
   ``PATTERNS`` phrases, and the block's texts are streamed through all of them, whole. Around each place that an automaton finds, the text is compared
   with the first document's words: what is equal over a window or more goes, and nothing else does. So no mark, window or passage is a hot key, and a task holds one block and one shard.

Null and empty texts have no words. Documents of fewer words than a window lose none. Ids should be unique: rows that share an id
never make each other go, and where their texts differ, some of what only they hold may stay in others. Rows of a null id are kept whole, and make nothing else go.
Ties don't arise: the smallest id decides. Repeated words and very long texts need no special care. Columns beside id and text are ignored by ``removals`` and kept by ``without_passages``."""

from __future__ import annotations

import hashlib
import struct
from collections.abc import Callable, Iterator
from itertools import repeat

import ahocorasick
import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathtraces.llm.common import fresh, parts, rolling, spill, texts, word_hashes

WIDTH, PHRASE, BLOCK_BYTES, PATTERNS = 50, 16, 4 << 20, 10_000
_EMPTY = hashlib.sha256(b"").hexdigest()


def marks(hashes: np.ndarray, width: int = WIDTH, phrase: int = PHRASE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Mark, first and last window start, for each run of windows of one mark."""
    phrases = rolling(hashes, phrase)
    n = len(hashes) - width + 1
    if n < 1:
        return np.empty(0, np.int64), np.empty(0, np.int32), np.empty(0, np.int32)
    span = width - phrase + 1
    at = np.empty(n, np.int64)
    for a in range(0, n, 1 << 15):
        b = min(n, a + (1 << 15))
        at[a:b] = np.lib.stride_tricks.sliding_window_view(phrases[a : b + span - 1], span).min(axis=1).view(np.int64)
    first = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
    return at[first], first.astype(np.int32), np.concatenate([first[1:], [n]]).astype(np.int32) - 1


def marked(docs: DataFrame, width: int, phrase: int) -> DataFrame:
    """Per row: ``id``, ``key1`` and ``key2`` (of its words), ``n_words``, ``n_bytes``, ``kept_sha256`` (of all its words), ``marks`` (each once)."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for piece in parts(batch):
                rows = []
                for text in texts(piece.column(1)):
                    words = (text or b"").split()
                    digest = hashlib.sha256(b" ".join(words))
                    rows.append((*struct.unpack("<qq", digest.digest()[:16]), len(words), len(text or b""), digest.hexdigest(), np.unique(marks(word_hashes(words), width, phrase)[0])))
                cols = list(zip(*rows, strict=True))
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.int64())]
                yield pa.RecordBatch.from_arrays([piece.column(0), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], names)

    names = ["id", "key1", "key2", "n_words", "n_bytes", "kept_sha256", "marks"]
    return docs.mapInArrow(run, "id long, key1 long, key2 long, n_words long, n_bytes long, kept_sha256 string, marks array<long>")


def snippets(docs: DataFrame, wanted: DataFrame, width: int, phrase: int) -> DataFrame:
    """``docs`` (id, text) around the wanted marks (``id``, ``marks``): ``mark``, ``id``, ``first`` (word), ``words``, ``windows`` (hashes)."""

    def run(batches):
        import pyarrow as pa

        kinds = [pa.int64(), pa.int64(), pa.int32(), pa.string(), pa.list_(pa.int64())]
        for batch in batches:
            for piece in parts(batch, 64):
                rows = []
                for key, text, some in zip(piece.column(0).to_pylist(), texts(piece.column(1)), piece.column(2).to_pylist(), strict=True):
                    words = text.split()
                    hashes = word_hashes(words)
                    windows = rolling(hashes, width).view(np.int64)
                    found, firsts, lasts = marks(hashes, width, phrase)
                    for k in np.flatnonzero(np.isin(found, some)).tolist():
                        a, b = int(firsts[k]), int(lasts[k])
                        rows.append((int(found[k]), key, a, b" ".join(words[a : b + width]).decode(), windows[a : b + 1]))
                cols = list(zip(*rows, strict=True)) or [[]] * 5
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["mark", "id", "first", "words", "windows"])

    return docs.join(wanted, "id").mapInArrow(run, "mark long, id long, first int, words string, windows array<long>")


class PhraseAutomaton:
    """Aho-Corasick over words: a word is one symbol, a pattern is a phrase. Under each phrase stand the passages that hold it: first document, coded words, place of the phrase."""

    def __init__(self):
        self.symbols: dict[bytes, str] = {}
        self.automaton = ahocorasick.Automaton(ahocorasick.STORE_ANY)
        self.size = 0

    def coded(self, words: list[bytes]) -> str:
        """The words of a passage, one character each; surrogates are left out."""
        known = self.symbols
        for w in words:
            if w not in known:
                n = len(known) + 2
                known[w] = chr(n + 2048 if n >= 0xD800 else n)
        return "".join(map(known.__getitem__, words))

    def add(self, first: int, passage: str, at: int, phrase: int) -> None:
        key = passage[at : at + phrase]
        if key not in self.automaton:
            self.automaton.add_word(key, (phrase, []))
        self.automaton.get(key)[1].append((first, passage, at))
        self.size += 1

    def cover(self, key: int, words: list[bytes], gone: bytearray, width: int) -> None:
        """Marks in ``gone`` the words of document ``key`` that lie in a run of ``width`` or more words which is in a passage of an earlier document. The automaton
        finds the phrases; around each, words are compared as far as they are equal."""
        text = "".join(map(self.symbols.get, words, repeat("\x01")))
        for end, (phrase, passages) in self.automaton.iter(text):
            d = end + 1 - phrase
            for first, passage, at in passages:
                if first >= key:
                    continue
                if gone.find(0, max(0, d + phrase - width), d + width) < 0:
                    break  # every window around it goes already
                low = at - _shared(passage[:at][::-1], text[max(0, d - at) : d][::-1])
                high = at + _shared(passage[at:], text[d : d + len(passage) - at])
                if high - low >= width:
                    gone[d - at + low : d - at + high] = b"\1" * (high - low)


def _shared(a: str, b: str) -> int:
    """How many characters two texts begin with alike."""
    n = min(len(a), len(b))
    if a[:n] == b[:n]:
        return n
    low, high = 0, n  # alike up to low, not up to high
    while high - low > 1:
        middle = (low + high) // 2
        low, high = (middle, high) if a[:middle] == b[:middle] else (low, middle)
    return low


def phrase_places(words: list[bytes], mark: int, starts: list[int], width: int, phrase: int) -> list[int]:
    """Places of the mark's phrase, so that each of the windows holds one of them."""
    at = np.flatnonzero(rolling(word_hashes(words), phrase).view(np.int64) == mark)
    out: list[int] = []
    for k in sorted(starts):
        if not out or out[-1] < k:
            out.append(int(at[np.searchsorted(at, k + width - phrase, "right") - 1]))
    return out


def shards(pieces: list[tuple[int, list[bytes], int, list[int]]], width: int, phrase: int, patterns: int) -> Iterator[PhraseAutomaton]:
    """Automata of about ``patterns`` phrases each, over pieces of text: (first document, words, mark, starts of the windows)."""
    now = PhraseAutomaton()
    for first, words, mark, starts in pieces:
        if now.size >= patterns:
            now.automaton.make_automaton()
            yield now
            now = PhraseAutomaton()
        passage = now.coded(words)
        for at in phrase_places(words, mark, starts, width, phrase):
            now.add(first, passage, at, phrase)
    if now.size:
        now.automaton.make_automaton()
        yield now


def covered(ids: list[int | None], each: list[list[bytes]], pieces: list, width: int, phrase: int, patterns: int) -> list[np.ndarray | None]:
    """For each text which of its words go (none: nothing goes), after it went through all shards."""
    gone = [bytearray(len(words)) for words in each]
    for automaton in shards(pieces, width, phrase, patterns):
        for key, words, mine in zip(ids, each, gone, strict=True):
            if key is not None and len(words) >= width:
                automaton.cover(key, words, mine, width)
    return [np.frombuffer(mine, bool) if 1 in mine else None for mine in gone]


def routed(plain: DataFrame, width: int, phrase: int, block_bytes: int) -> tuple[DataFrame, DataFrame, int]:
    """Per document: ``id``, ``n_words``, ``kept_sha256`` (of all its words), ``first_of`` (smallest id of its text). Per block the pieces to look for: ``block``,
    ``first`` (document), ``words``, ``mark``, ``starts`` (of the windows in them). And the number of blocks."""
    base = spill(marked(plain, width, phrase), "marks")
    blocks = max(1, -(-(base.agg(F.sum("n_bytes")).first()[0] or 0) // block_bytes))
    keyed = base.where("id is not null")
    one = spill(keyed.groupBy("key1", "key2").agg(F.min("id").alias("first_of")), "texts")  # stored, so that the join can split many copies
    named = keyed.select("id", "n_words", "key1", "key2", "kept_sha256").join(one, ["key1", "key2"])
    nameless = base.where("id is null").select("id", "n_words", "kept_sha256", F.lit(None).cast("long").alias("first_of"))
    named = spill(named.select("id", "n_words", "kept_sha256", "first_of").unionByName(nameless), "named")
    lone = named.where("id = first_of").select("id").distinct()
    each = keyed.select("id", F.explode("marks").alias("mark")).join(lone, "id", "left_semi")
    often = each.groupBy("mark").agg(F.min("id").alias("a"), F.max("id").alias("b")).where("a != b").select("mark")
    wanted = each.join(often, "mark", "left_semi").groupBy("id").agg(F.collect_set("mark").alias("marks"))
    cut = spill(snippets(plain, wanted, width, phrase), "snippets")
    windows = cut.select("mark", "id", F.col("first").alias("at"), F.posexplode("windows").alias("k", "w"))
    met = windows.groupBy("mark", "w", block_of("id", blocks).alias("block")).agg(F.min(F.struct("id", "at", "k")).alias("first"), F.max("id").alias("last"))
    met = spill(met, "windows")  # a window of many documents is one row a block
    known = met.groupBy("mark", "w").agg(F.min("first").alias("origin"), F.max("last").alias("other")).where("origin.id != other").select("mark", "w", "origin")
    routes = met.join(known, ["mark", "w"]).where("last != origin.id").groupBy("block", "origin.id", "mark", "origin.at").agg(F.collect_set("origin.k").alias("starts"))
    routes = spill(routes, "routes")
    pieces = cut.join(routes.select("id", "mark", F.col("at").alias("first")).distinct(), ["id", "mark", "first"], "left_semi")
    pieces = spill(pieces.select("id", "mark", F.col("first").alias("at"), "words").dropDuplicates(["id", "mark", "at"]), "pieces")
    return named, routes.join(pieces, ["id", "mark", "at"]).select("block", F.col("id").alias("first"), "words", "mark", "starts"), blocks


def block_of(id: str, blocks: int, other: Column | None = None) -> Column:
    """The block of a document; rows without an id are dealt out by ``other``."""
    key = F.col(id).cast("long")
    h = F.xxhash64(key) if other is None else F.when(key.isNotNull(), F.xxhash64(key)).otherwise(F.xxhash64(other))
    return F.pmod(h, F.lit(blocks)).cast("long")


def streamed(docs: DataFrame, pieces: DataFrame, blocks: int, id: str, text: str, width: int, phrase: int, finish: Callable, schema, patterns: int | None = None) -> DataFrame:
    """All texts through the automata of their block. ``finish`` gets a block's Arrow table, the words of each text, and which of them go (None: nothing)."""
    name, limit = fresh(docs, "__block"), patterns or PATTERNS
    at = docs.columns.index(text), docs.columns.index(id)

    def run(left, right):
        table = left.select(list(range(left.num_columns - 1)))
        each = [(t or b"").split() for t in texts(left.column(at[0]).combine_chunks())]
        found = [(f, w.encode().split(b" "), m, s) for f, w, m, s in zip(*(right[c].to_pylist() for c in ("first", "words", "mark", "starts")), strict=True)]
        return finish(table, each, covered(left.column(at[1]).to_pylist(), each, found, width, phrase, limit))

    dealt = docs.withColumn(name, block_of(id, blocks, F.col(text)))
    return dealt.groupBy(name).cogroup(pieces.groupBy("block")).applyInArrow(run, schema)


def _left(words: list[bytes], gone: np.ndarray) -> bytes:
    return b" ".join([words[k] for k in np.flatnonzero(~gone).tolist()])


def _plain(docs: DataFrame, id: str, text: str, width: int, phrase: int) -> DataFrame:
    if not phrase <= width:
        raise ValueError("a phrase is at most as long as a window")
    return docs.select(F.col(id).cast("long").alias("id"), F.col(text).alias("text"))


def removals(docs: DataFrame, id: str = "doc_id", text: str = "text", width: int = WIDTH, phrase: int = PHRASE, block_bytes: int = BLOCK_BYTES, patterns: int | None = None) -> DataFrame:
    """Per row: ``id``, ``n_words``, ``n_removed``, ``kept_sha256``."""
    plain = _plain(docs, id, text, width, phrase)
    named, pieces, blocks = routed(plain, width, phrase, block_bytes)
    copies = (F.col("id") != F.col("first_of")) & (F.col("n_words") >= width)

    def finish(table, each, gone):
        import pyarrow as pa

        rows = [(key, hashlib.sha256(b" ".join(w)).hexdigest(), int(g.sum()), hashlib.sha256(_left(w, g)).hexdigest()) for key, w, g in zip(table.column(0).to_pylist(), each, gone, strict=True) if g is not None]
        cols = list(zip(*rows, strict=True)) or [[]] * 4
        return pa.table({n: pa.array(c, k) for n, c, k in zip(("id", "kept_sha256", "gone", "sha"), cols, (pa.int64(), pa.string(), pa.int64(), pa.string()), strict=True)})

    changed = streamed(plain, pieces, blocks, "id", "text", width, phrase, finish, "id long, kept_sha256 string, gone long, sha string", patterns).dropDuplicates(["id", "kept_sha256"])
    out = named.join(changed, ["id", "kept_sha256"], "left").select("id", "n_words", F.when(copies, F.col("n_words")).otherwise(F.coalesce("gone", F.lit(0))).cast("long").alias("n_removed"), F.when(copies, F.lit(_EMPTY)).otherwise(F.coalesce("sha", "kept_sha256")).alias("kept_sha256"))
    return out.withColumnRenamed("id", id)


def without_passages(docs: DataFrame, id: str = "doc_id", text: str = "text", width: int = WIDTH, phrase: int = PHRASE, block_bytes: int = BLOCK_BYTES, patterns: int | None = None) -> DataFrame:
    """``docs`` with the passages taken out of their texts: what is left of a changed text are its words, joined by single spaces.
    Documents of which nothing is left go; those that had no words before stay as they are."""
    named, pieces, blocks = routed(_plain(docs, id, text, width, phrase), width, phrase, block_bytes)
    copy = fresh(docs, "__id")
    copies = named.where((F.col("id") != F.col("first_of")) & (F.col("n_words") >= width)).select(F.col("id").alias(copy)).distinct()
    at = docs.columns.index(text)

    def finish(table, each, gone):
        import pyarrow as pa

        column = table.column(at).combine_chunks()
        new = [t if g is None else _left(w, g).decode() or None for t, w, g in zip(column.to_pylist(), each, gone, strict=True)]
        stays = pa.array([g is None or t is not None for t, g in zip(new, gone, strict=True)], pa.bool_())
        return table.set_column(at, table.schema.field(at), pa.array(new, column.type)).filter(stays)

    return streamed(docs.join(copies, F.col(id) == F.col(copy), "left_anti"), pieces, blocks, id, text, width, phrase, finish, docs.schema, patterns)
