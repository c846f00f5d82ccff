"""Best-two-fit packing of token sequences.

Packing needs only how many pieces have each length (at most `capacity` numbers): bins are planned on that
histogram as patterns with multiplicities, and pieces are dealt to planned places by their rank among the
pieces of their length. Only the tokeniser runs in Python over texts; nothing that grows with the corpus is collected.
"""

from __future__ import annotations

import json
import os
import re
import sys
import zlib
from array import array
from bisect import bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import kept, written

#: Entries of a worker's cache of tokenised chunks; when it is full it is emptied. It changes no result.
CACHE = 800_000
PIECES = "task int, doc_id long, piece int, start long, length long, ids_crc32 long, local_rank long"


#: Characters of which NFC keeps every text as it is and whose lower-case forms are one character each, whatever stands beside them.
PLAIN = re.compile("[!-~\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u012f\u0131-\u0148\u014a-\u017f]*\\Z")


def byte_letters() -> dict[int, str]:
    """For each byte the character that byte-level vocabularies write it as: printable ones stand for themselves, the rest follow from 256 on."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [x for x in range(256) if x not in own]
    return {x: chr(x) for x in own} | {x: chr(256 + k) for k, x in enumerate(rest)}


class WordModel:
    """The model of a tokenizer that normalises by NFC, white space and lower case, splits by one pattern and maps bytes to letters.

    Its steps are done here for plain chunks, so that the model alone has to be asked, once for each word.
    """

    def __init__(self, tokenizer, pattern: str) -> None:
        # Of plain lower-case chunks these are all letters and digits there are.
        own = pattern.replace(r"\p{L}", "a-z\u00df-\u00f6\u00f8-\u017f").replace(r"\p{N}", "0-9")
        self.model, self.words, self.letters, self.cache = tokenizer.model, re.compile(own).findall, byte_letters(), {}

    @classmethod
    def of(cls, tokenizer) -> WordModel | None:
        made = json.loads(tokenizer.to_str())
        steps = (made.get("normalizer") or {}).get("normalizers") or []
        parts = (made.get("pre_tokenizer") or {}).get("pretokenizers") or []
        lower = [x["type"] for x in steps] == ["NFC", "Replace", "Lowercase"] and steps[1]["pattern"] == {"Regex": "\\s+"}
        split = [x["type"] for x in parts] == ["Split", "ByteLevel"] and parts[0]["invert"] and parts[0]["behavior"] == "Removed" and not parts[1]["add_prefix_space"] and not parts[1]["use_regex"]
        if not (lower and split and made.get("post_processor") is None):
            return None
        pattern = parts[0]["pattern"]["Regex"]
        bare = re.sub(r"\[[^\]]*\]", "", pattern)  # classes may stand inside brackets only
        return cls(tokenizer, pattern) if "\\" not in bare and not re.search(r"\\(?!s|p\{[LN]\})", pattern) else None

    def ids(self, chunk: str) -> bytes:
        out = []
        for w in self.words(chunk.lower()):
            if (got := self.cache.get(w)) is None:
                written = w if w.isascii() else w.encode().decode("latin1").translate(self.letters)
                got = self.cache[w] = array("I", [t.id for t in self.model.tokenize(written)]).tobytes()
            out.append(got)
        return out[0] if len(out) == 1 else b"".join(out)


class ChunkTokenizer:
    """Token ids of a text as little-endian unsigned 32-bit numbers, chunk by chunk.

    For tokenizers that drop white space and never join across it: blanks and line feeds split the text,
    and the ids of the chunks are joined. Chunks repeat a lot, so each is tokenised once. Plain chunks go to the model by
    WordModel where the tokenizer is of that kind, all others and those that may hold a special token through the whole tokenizer.
    """

    def __init__(self, path: str) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer, self.cache = Tokenizer.from_file(path), {"": b""}
        added = list(self.tokenizer.get_added_tokens_decoder().items())
        special = [(t.content, i) for i, t in added if t.special and not (t.lstrip or t.rstrip)]
        self.mark, self.mark_id = special[0] if special else (None, -1)
        self.starts = {t.content[:2] for _, t in added}
        self.plain = WordModel.of(self.tokenizer) if array("I").itemsize == 4 and sys.byteorder == "little" else None

    def ids(self, text: str) -> bytes:
        chunks = text.replace("\n", " ").split(" ")
        try:
            return b"".join(map(self.cache.__getitem__, chunks))
        except KeyError:
            pass
        if len(self.cache) > CACHE:
            self.cache = {"": b""}
            if self.plain:
                self.plain.cache.clear()
        new = [c for c in set(chunks) if c not in self.cache]
        if self.plain:
            rest = []
            for c in new:
                if PLAIN.match(c) and not any(x in c for x in self.starts):
                    self.cache[c] = self.plain.ids(c)
                else:
                    rest.append(c)
            new = rest
        if new:
            self._encode(new)
        return b"".join(map(self.cache.__getitem__, chunks))

    def _encode(self, new: list[str]) -> None:
        """Many chunks in one call, parted by a special token that none of them holds; one by one where that cannot be."""
        if self.mark and not any(self.mark[:2] in c for c in new):
            ids = np.asarray(self.tokenizer.encode(self.mark.join(new), add_special_tokens=False).ids, dtype="<u4")
            ends = np.flatnonzero(ids == self.mark_id)
            if len(ends) == len(new) - 1:
                raw, at = ids.tobytes(), 0
                for c, end in zip(new, [*ends.tolist(), len(ids)], strict=True):
                    self.cache[c] = raw[4 * at : 4 * end]
                    at = end + 1
                return
        for c, e in zip(new, self.tokenizer.encode_batch(new, add_special_tokens=False), strict=True):
            self.cache[c] = np.asarray(e.ids, dtype="<u4").tobytes()


def tokenizer(path: str) -> ChunkTokenizer:
    """A worker keeps its tokenizer and cache from task to task, until another operator needs the memory."""
    return kept(f"tokenizer {path}", lambda: ChunkTokenizer(path))


def cut(docs: DataFrame, tokenizer_path: str, capacity: int = 2048, end_id: int = 0) -> DataFrame:
    """docs(doc_id, text) -> the pieces of each document and their rank among the task's pieces of that length."""
    end = np.asarray([end_id], dtype="<u4").tobytes()

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok, ranks, task = tokenizer(tokenizer_path), np.zeros(capacity + 1, dtype=np.int64), TaskContext.get().partitionId()
        for b in batches:
            out = []
            for doc, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                ids = tok.ids(text.as_py() or "") + end
                for k, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    n = len(part) // 4
                    out.append((task, doc, k, at // 4, n, zlib.crc32(part), int(ranks[n])))
                    ranks[n] += 1
            if out:
                types = (pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64())
                names = ["task", "doc_id", "piece", "start", "length", "ids_crc32", "local_rank"]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(pieces, PIECES)


def plan(counts: dict[int, int], capacity: int) -> list[tuple[list[int], int]]:
    """Patterns (lengths, how many bins) that use up a histogram of lengths.

    Each bin takes the longest piece left, then again and again the longest that fits its gap. Then its smallest
    piece is taken out if two pieces that are still unpacked fill the wider gap better than it did.
    """
    left = {n: c for n, c in counts.items() if c > 0}
    lengths = sorted(left)
    patterns = []

    def largest(gap: int, used: dict[int, int]) -> int | None:
        i = bisect_right(lengths, gap) - 1
        while i >= 0 and left[lengths[i]] <= used.get(lengths[i], 0):
            i -= 1
        return lengths[i] if i >= 0 else None

    while lengths:
        used: dict[int, int] = {}
        slots: list[int] = []
        gap = capacity
        while gap and (n := largest(gap, used)) is not None:
            fits = max(1, min(gap // n, left[n] - used.get(n, 0)))
            slots += [n] * fits
            used[n] = used.get(n, 0) + fits
            gap -= n * fits
        if gap and len(slots) > 1:
            small = slots[-1]
            used[small] -= 1
            wide, best = gap + small, (small, None)
            free = [n for n in lengths[: bisect_right(lengths, wide)] if left[n] > used.get(n, 0)]
            i, j = 0, len(free) - 1
            while i <= j:
                a, b = free[i], free[j]
                if a + b > wide:
                    j -= 1
                elif i == j and left[a] - used.get(a, 0) < 2:
                    break
                else:
                    if a + b > best[0]:
                        best = (a + b, (b, a))
                    i += 1
            if best[1]:
                slots = [*slots[:-1], *best[1]]
                for n in best[1]:
                    used[n] = used.get(n, 0) + 1
            else:
                used[small] += 1
        used = {n: k for n, k in used.items() if k}
        times = min(left[n] // k for n, k in used.items())
        patterns.append((slots, times))
        for n, k in used.items():
            left[n] -= k * times
        lengths = [n for n in lengths if left[n]]
    return patterns


def places(patterns: list[tuple[list[int], int]]) -> tuple[np.ndarray, ...]:
    """For each slot of each pattern: length and first rank (as one sorted key), first sequence, place in it."""
    rows, cursor, sequence = [], {}, 0
    for slots, times in patterns:
        at = 0
        for n in slots:
            first = cursor.get(n, 0)
            rows.append(((n << 44) + first, first, sequence, at))
            cursor[n] = first + times
            at += n
        sequence += times
    rows.sort()
    return tuple(np.asarray(c, dtype=np.int64) for c in zip(*rows, strict=True)) if rows else tuple(np.zeros(0, np.int64) for _ in range(4))


def pack(docs: DataFrame, tokenizer_path: str, capacity: int = 2048, end_id: int = 0) -> DataFrame:
    """docs(doc_id, text, ...) -> doc_id, piece, start, length, ids_crc32, sequence_id, offset: a row for each piece.

    Every document ends with `end_id`, so that null and empty texts are one piece of one token. Only documents longer
    than `capacity` are cut, into full pieces and a last one. Repeated rows are packed as often as they come.
    An empty table gives no rows; extra columns are ignored.
    """
    made = written(cut(docs, tokenizer_path, capacity, end_id), "pieces")
    counts = made.groupBy("task", "length").agg(F.count("*").alias("n"))
    before = W.partitionBy("length").orderBy("task").rowsBetween(W.unboundedPreceding, -1)
    bases = written(counts.withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0))), "ranks")
    found = {r[0]: r[1] for r in bases.groupBy("length").agg(F.sum("n")).collect()}  # `capacity` rows at most
    keys, firsts, sequences, offsets = places(plan(found, capacity))
    names = ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]

    def placed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n, rank = b.column("length").to_numpy(), b.column("rank").to_numpy()
            i = np.searchsorted(keys, (n << 44) + rank, side="right") - 1
            own = [b.column(c) for c in names[:5]]
            yield pa.RecordBatch.from_arrays([*own, pa.array(sequences[i] + rank - firsts[i]), pa.array(offsets[i])], names)

    ranked = made.join(bases.select("task", "length", "base"), ["task", "length"]).select(*names[:5], (F.col("base") + F.col("local_rank")).alias("rank"))
    return ranked.mapInArrow(placed, "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
