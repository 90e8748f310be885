"""Packing token sequences: shortest pack first over the histogram of lengths.

Lengths are placed longest first; all pieces of one length go, as counts, to the packs
that hold the fewest tokens so far. Only the histogram (at most ``limit`` rows) and the
resulting pattern counts are on the driver. Pieces meet patterns again by their rank
within their length, found from counts per (length, salt), so a length that a third of
all pieces share is ranked in many tasks.

Defined cases: null or empty text is one piece, its end id alone; a text over the limit
is cut into full pieces and a rest; repeated rows are separate documents whose pieces
are told apart by ``row_id``, a number of the input row; empty tables give no rows;
further columns are ignored.
"""

from __future__ import annotations

import heapq
import json
import re
import unicodedata
import zlib
from itertools import chain, filterfalse

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from prunegraph.llm.common import materialize, salt, width

LIMIT = 4096
END = 2
#: Words kept per worker, in two halves: the older one goes when the younger is full.
KNOWN_WORDS = 1_000_000

#: Letters, then other marks to the end: the vocabulary never joins across that border.
_LETTERS_THEN_MARKS = re.compile(r"([^\W\d_]+)([^\w\s]+)")
#: A word of its own, of one id that no other text gives; it parts words encoded in one call.
_BORDER = "\x01"
_AT_ONCE = 200


class WordTokens:
    """Ids of whole texts, word by word with memory; equal to encoding the text at once.

    The vocabulary drops white space and never joins across it, so texts are cut there and
    each word is encoded once; letters with marks behind them are two parts that are encoded
    once each. Words are cut from composed text, so only their lower case is left to the
    vocabulary's own rules, and nothing if they are ASCII. Texts that are not in composed
    form, hold a letter whose lower case depends on its surroundings or may hold a
    control token are encoded whole."""

    def __init__(self, path: str, known: int = KNOWN_WORDS):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as file:
            rules = json.load(file)
        self.tokenizer, self.known = Tokenizer.from_file(path), known
        self.plain = Tokenizer.from_str(json.dumps(rules | {"normalizer": None}))
        # words of letters alone are one part each: white space cuts them as the vocabulary's pattern does
        byte_level = rules["pre_tokenizer"]["pretokenizers"][-1]
        letters = {"type": "Sequence", "pretokenizers": [{"type": "WhitespaceSplit"}, byte_level]}
        self.letters = Tokenizer.from_str(json.dumps(rules | {"normalizer": None, "pre_tokenizer": letters}))
        self.lower = Tokenizer.from_str(json.dumps(rules | {"normalizer": {"type": "Lowercase"}}))
        self.border = self.plain.encode(_BORDER, add_special_tokens=False).ids[0]
        self.ids, self.older = {"": b""}, {}

    def encoded(self, words: list[str]) -> dict[str, bytes]:
        """Ids of single words, many of them in one call."""
        found = {}
        kinds = {self.letters: [], self.plain: [], self.lower: []}
        for word in words:
            kind = self.lower if not word.isascii() else self.letters if word.isalpha() else self.plain
            kinds[kind].append(word)
        for rules, some in kinds.items():
            alone = [[w] for w in some if _BORDER in w]
            some = [w for w in some if _BORDER not in w]
            groups = alone + [some[at : at + _AT_ONCE] for at in range(0, len(some), _AT_ONCE)]
            for group, coded in zip(groups, rules.encode_batch_fast([f" {_BORDER} ".join(g) for g in groups], add_special_tokens=False)):
                ids = np.array(coded.ids, "<u4")
                at = 4 * np.flatnonzero(ids == self.border) if len(group) > 1 else np.zeros(0, np.int64)
                flat = ids.tobytes()
                found.update(zip(group, (flat[i:j] for i, j in zip([0, *(at + 4).tolist()], [*at.tolist(), len(flat)]))))
        return found

    def learn(self, words: set[str]) -> None:
        """Puts ids of ``words`` into memory."""
        ids, older, new, cut = self.ids, self.older, set(), []
        for word in words:
            if word in older:
                ids[word] = older[word]
            elif parts := _LETTERS_THEN_MARKS.fullmatch(word):
                cut.append((word, *parts.groups()))
                for part in parts.groups():
                    if part in older:
                        ids[part] = older[part]
                    elif part not in ids:
                        new.add(part)
            else:
                new.add(word)
        ids.update(self.encoded(list(new)))
        for word, letters, marks in cut:
            ids[word] = ids[letters] + ids[marks]

    def texts(self, texts: list[str]) -> list[bytes]:
        parts, whole = [], {}
        for i, text in enumerate(texts):
            if (text.isascii() or unicodedata.is_normalized("NFC", text) and "Σ" not in text and "İ" not in text) and "<|" not in text:
                parts.append(text.lower().replace("\n", " ").split(" "))
            else:
                whole[i] = np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
                parts.append([])
        if len(self.ids) > self.known // 2:
            self.older, self.ids = self.ids, {"": b""}
        self.learn(set(filterfalse(self.ids.__contains__, chain.from_iterable(parts))))
        get = self.ids.__getitem__
        return [whole[i] if i in whole else b"".join(map(get, words)) for i, words in enumerate(parts)]


_tokens: dict[str, WordTokens] = {}


def tokens_of(path: str) -> WordTokens:
    if path not in _tokens:
        _tokens[path] = WordTokens(path)
    return _tokens[path]


_PIECE = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "row_id"]


def pieces(docs: DataFrame, tokenizer_path: str, limit: int = LIMIT, end: int = END) -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens, row_id for each piece of each document."""
    last = np.array([end], "<u4").tobytes()

    def cut(batches):
        import os

        from pyspark import TaskContext

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        tokens, row = tokens_of(tokenizer_path), TaskContext.get().partitionId() << 40
        for batch in batches:
            ids, texts = batch.column(0), batch.column(1)
            for at in range(0, batch.num_rows, 256):
                out = []
                some = [t or "" for t in texts.slice(at, 256).to_pylist()]
                for doc, coded in zip(ids.slice(at, 256).to_pylist(), tokens.texts(some)):
                    coded += last
                    n = len(coded) // 4
                    out += [(doc, s, min(limit, n - s), zlib.crc32(coded[4 * s : 4 * (s + limit)]), n, row) for s in range(0, n, limit)]
                    row += 1
                columns = list(zip(*out))
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], _PIECE)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(cut, ", ".join(f"{c} long" for c in _PIECE))


def pack_histogram(lengths: np.ndarray, counts: np.ndarray, limit: int = LIMIT) -> dict[str, np.ndarray]:
    """Shortest pack first over a histogram.

    Returns runs, ordered by (length, first): ``count`` pieces of ``length`` with ranks
    from ``first`` lie at ``offset`` of the packs numbered from ``pack``. A pack group is
    a range of pack numbers with equal content; placing a length on part of a group
    splits the range."""
    group: list[tuple[int, int, int]] = []  # (tokens so far, first pack, packs)
    made, runs = 0, []
    for length, n in sorted(zip(lengths.tolist(), counts.tolist()), reverse=True):
        first = 0
        while n:
            if group and group[0][0] + length <= limit:
                used, pack, packs = heapq.heappop(group)
                m = min(n, packs)
                if m < packs:
                    heapq.heappush(group, (used, pack + m, packs - m))
            else:
                used, pack, m = 0, made, n
                made += n
            runs.append((length, first, m, pack, used))
            if used + length < limit:
                heapq.heappush(group, (used + length, pack, m))
            first, n = first + m, n - m
    table = np.array(sorted(runs), np.int64).reshape(-1, 5)
    return dict(zip(("length", "first", "count", "pack", "offset"), table.T.copy()))


def pack(cut: DataFrame, limit: int = LIMIT) -> DataFrame:
    """Adds sequence_id and offset to ``pieces``; a materialised input is best."""
    spark = cut.sparkSession
    salts = width(spark)
    salted = cut.withColumn("salt", salt(F.col("row_id"), F.col("start"), n=salts))
    counts = salted.groupBy("length", "salt").agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0)))
    counts = materialize(counts, "length-counts")
    # at most ``limit`` rows: one per length
    histogram = counts.groupBy("length").agg(F.sum("n").alias("n")).collect()
    runs = pack_histogram(np.array([r[0] for r in histogram], np.int64), np.array([r[1] for r in histogram], np.int64), limit)
    shared = spark.sparkContext.broadcast(runs)

    def join(batches):
        at = shared.value
        key = (at["length"] << 40) | at["first"]
        for batch in batches:
            length, rank = (batch.column(i).to_numpy(zero_copy_only=False) for i in (2, 6))
            k = np.searchsorted(key, (length << 40) | rank, "right") - 1
            yield pa.RecordBatch.from_arrays(
                [*batch.columns[:6], pa.array(at["pack"][k] + rank - at["first"][k]), pa.array(at["offset"][k])],
                [*_PIECE, "sequence_id", "offset"],
            )

    order = Window.partitionBy("length", "salt").orderBy("doc_id", "start", "row_id")
    ranked = (
        salted.withColumn("k", F.row_number().over(order) - 1)
        # the counts grow with the salts: merged where the window has put the rows already
        .join(counts.select("length", "salt", "base").hint("merge"), ["length", "salt"])
        .select(*_PIECE, (F.col("base") + F.col("k")).alias("rank"))
    )
    return ranked.mapInArrow(join, ", ".join(f"{c} long" for c in [*_PIECE, "sequence_id", "offset"]))


def pack_documents(docs: DataFrame, tokenizer_path: str, limit: int = LIMIT, end: int = END) -> DataFrame:
    return pack(materialize(pieces(docs, tokenizer_path, limit, end), "pieces"), limit)
