"""Language-model scores by context-tree weighting over bytes.

Each byte is eight binary decisions; each decision has a tree of the bytes before it, whose nodes mix their own
Krichevsky-Trofimov estimate with their children's, half and half. Trees are built from the counts of all byte
sequences of the training texts, gathered by one shuffle. The model is a table: for every depth and every sequence
seen, the mixed probability of its last byte after the others, and for every context what is left for bytes that
never followed it. That rest is spread over those bytes as the next shorter context has them, so that the 256
probabilities after any context sum to one.

Texts are scored as their lower-cased words with one blank between, and a line feed as the end.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_mod, py_crc_mod, written

DEPTH = 5
END = b"\n"
STEP = 1 << 20
#: Entries of a table that is sent to every worker (16 bytes each there). A larger one stays distributed, with the same scores.
MAX_ENTRIES = 8_000_000
#: Characters of the texts that ask a distributed table together.
CHUNK = 8 << 20
#: Most frequent words, whose counts are sent to every worker; other words meet their counts in a join.
FREQUENT = 200_000
_U = np.uint64
_TAG = _U(56)  # a key's top byte: depth + 1 for a sequence, 128 + depth for a context


def stream(text: str | None) -> tuple[list[bytes], bytes]:
    """Lower-cased words (A-Z only, ASCII white space) and the bytes that are scored."""
    w = (text or "").encode("utf-8", "surrogatepass").lower().split()
    return w, b" ".join(w) + END


def sequences(data: np.ndarray, depth: int) -> np.ndarray:
    """For each byte from place `depth` on: the byte before it, the one before that, ..., and the byte, as one number."""
    n = len(data) - depth
    x = data.astype(np.uint64)
    key = x[depth : depth + n].copy()
    for d in range(1, depth + 1):
        key |= x[depth - d : depth - d + n] << _U(8 * (depth + 1 - d))
    return key


def _steps(data: bytes, depth: int) -> Iterator[np.ndarray]:
    whole = np.frombuffer(data, np.uint8)
    for at in range(0, len(whole) - depth, STEP):
        yield sequences(whole[at : at + STEP + depth], depth)


def _merged(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    o = np.argsort(keys, kind="stable")
    keys, counts = keys[o], counts[o]
    new = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
    return keys[new], np.add.reduceat(counts, new)


def gram_counts(docs: DataFrame, depth: int) -> DataFrame:
    """(key, n) over all texts: how often each byte came after each `depth` bytes."""

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, counts, waiting, size = np.zeros(0, np.uint64), np.zeros(0, np.int64), [], 0
        pad = END * depth

        def take() -> None:
            nonlocal keys, counts
            found = []
            for t in waiting:
                found += list(_steps(t, depth))
            new = np.sort(np.concatenate(found))
            at = np.flatnonzero(np.concatenate(([True], new[1:] != new[:-1])))
            keys, counts = _merged(np.concatenate((keys, new[at])), np.concatenate((counts, np.diff(np.append(at, len(new))))))

        def out() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(counts)], ["key", "n"])

        for b in batches:
            for text in b.column(0):
                t = pad + stream(text.as_py())[1]
                waiting.append(t)
                size += len(t)
                if size >= 2 * STEP:
                    take()
                    waiting, size = [], 0
                    if len(keys) > 1_000_000:
                        yield out()
                        keys, counts = keys[:0], counts[:0]
        if waiting:
            take()
        if len(keys):
            yield out()

    return docs.select("text").mapInArrow(counted, "key long, n long").groupBy("key").agg(F.sum("n").alias("n"))


def log_gamma(x: np.ndarray) -> np.ndarray:
    shift = np.ones(len(x))
    for k in range(8):
        shift *= x + k
    y = x + 8
    return (y - 0.5) * np.log(y) - y + 0.5 * np.log(2 * np.pi) + 1 / (12 * y) - 1 / (360 * y**3) + 1 / (1260 * y**5) - np.log(shift)


def kt(zeros: np.ndarray, ones: np.ndarray) -> np.ndarray:
    """Log probability of a sequence of so many zeros and ones by the Krichevsky-Trofimov estimate."""
    return log_gamma(zeros + 0.5) + log_gamma(ones + 0.5) - log_gamma(zeros + ones + 1.0) - np.log(np.pi)


class BitTrees:
    """Context trees of one of the eight decisions, over sorted keys: nodes of each depth and their weights."""

    def __init__(self, keys: np.ndarray, counts: np.ndarray, depth: int, bit: int, least: int) -> None:
        byte = keys & _U(255)
        self.one = ((byte >> _U(7 - bit)) & _U(1)).astype(bool)
        prefix = byte >> _U(8 - bit) if bit else np.zeros(len(keys), np.uint64)
        self.least, self.node, first = least, {}, {}
        n = counts.astype(np.float64)
        for d in range(least, depth + 1):
            name = ((keys >> _U(8 * (depth + 1 - d))) << _U(8)) | prefix if d else prefix
            _, first[d], self.node[d] = np.unique(name, return_index=True, return_inverse=True)
        self.zeros = {d: np.bincount(i, weights=n * ~self.one) for d, i in self.node.items()}
        self.ones = {d: np.bincount(i, weights=n * self.one) for d, i in self.node.items()}
        self.own, self.mixed = {}, {}
        for d in range(depth, least - 1, -1):
            self.own[d] = kt(self.zeros[d], self.ones[d])
            self.mixed[d] = self.own[d]
            if d < depth:
                below = np.bincount(self.node[d][first[d + 1]], weights=self.mixed[d + 1], minlength=len(self.own[d]))
                self.mixed[d] = np.logaddexp(self.own[d], below) - np.log(2)
        self.top_first = first[least]

    def predicted(self, d: int) -> np.ndarray:
        """The estimate that each key's node of depth d has for the key's bit."""
        i = self.node[d]
        return (np.where(self.one, self.ones[d][i], self.zeros[d][i]) + 0.5) / (self.zeros[d][i] + self.ones[d][i] + 1.0)

    def weight(self, d: int) -> np.ndarray:
        return np.exp(np.log(0.5) + self.own[d] - self.mixed[d])[self.node[d]]


def top_nodes(depth: int) -> Callable:
    """Of all sequences after one byte: for each decision the counts and the mixed log probability."""
    schema = pa.schema([("bit", pa.int32()), ("prefix", pa.int64()), ("zeros", pa.float64()), ("ones", pa.float64()), ("mixed", pa.float64())])

    def made(table: pa.Table) -> pa.Table:
        keys, counts = _sorted(table)
        out = []
        for bit in range(8):
            t = BitTrees(keys, counts, depth, bit, 1)
            prefix = (keys[t.top_first] & _U(255)) >> _U(8 - bit)
            out.append(pa.table([pa.array(np.full(len(prefix), bit, np.int32)), pa.array(prefix.astype(np.int64)), pa.array(t.zeros[1]), pa.array(t.ones[1]), pa.array(t.mixed[1])], schema=schema))
        return pa.concat_tables(out)

    return made


def _sorted(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    keys = table.column("key").to_numpy().view(np.uint64)
    o = np.argsort(keys)
    return keys[o], table.column("n").to_numpy()[o]


def tabled(depth: int, roots: dict[tuple[int, int], tuple[float, float, float]]) -> Callable:
    """Of all sequences after one byte: the table's entries of depths 1 and more. roots: weight, zeros and ones by decision."""

    def made(table: pa.Table) -> pa.Table:
        keys, counts = _sorted(table)
        byte = keys & _U(255)
        log_q = {d: np.zeros(len(keys)) for d in range(depth + 1)}
        for bit in range(8):
            t = BitTrees(keys, counts, depth, bit, 1)
            prefix = (byte >> _U(8 - bit)).astype(np.int64) if bit else np.zeros(len(keys), np.int64)
            root = np.zeros((256, 3))
            for (b, p), values in roots.items():
                if b == bit:
                    root[p] = values
            w, zeros, ones = root[prefix].T
            p0 = (np.where(t.one, ones, zeros) + 0.5) / (zeros + ones + 1.0)
            log_q[0] += np.log(p0)
            done, left = w * p0, 1 - w
            for d in range(1, depth + 1):
                p = t.predicted(d)
                log_q[d] += np.log(done + left * p)
                if d < depth:
                    w = t.weight(d)
                    done, left = done + left * w * p, left * (1 - w)
        out_k, out_v = [], []
        for d in range(1, depth + 1):
            context = keys >> _U(8 * (depth + 1 - d))
            name = (context << _U(8)) | byte
            _, at = np.unique(name, return_index=True)
            q, shorter, own = np.exp(log_q[d][at]), np.exp(log_q[d - 1][at]), context[at]
            out_k.append(name[at] | (_U(d + 1) << _TAG))
            out_v.append(log_q[d][at])
            c, where = np.unique(own, return_inverse=True)
            out_k.append(c | (_U(128 + d) << _TAG))
            out_v.append(rest(np.bincount(where, weights=q), np.bincount(where, weights=shorter)))
        return pa.table([pa.array(np.concatenate(out_k).view(np.int64)), pa.array(np.concatenate(out_v).astype(np.float32))], ["key", "v"])

    return made


def rest(seen: np.ndarray, shorter: np.ndarray) -> np.ndarray:
    """Log of what unseen bytes' shorter probabilities are multiplied with."""
    return np.log(np.maximum(1 - seen, 1e-12)) - np.log(np.maximum(1 - shorter, 1e-12))


class Table:
    """Open-addressed lookups of 64-bit keys."""

    def __init__(self, keys: np.ndarray, values: np.ndarray, depth: int) -> None:
        self.depth = depth
        bits = max(4, int(np.ceil(np.log2(max(1, len(keys)) * 2))))
        self.shift, self.mask = _U(64 - bits), (1 << bits) - 1
        self.keys, self.values = np.zeros(1 << bits, np.uint64), np.zeros(1 << bits, np.float32)
        slot, left = self._slot(keys), np.arange(len(keys))
        while len(left):
            free = left[self.keys[slot[left]] == 0]
            self.keys[slot[free]] = keys[free]
            won = free[self.keys[slot[free]] == keys[free]]
            self.values[slot[won]] = values[won]
            settled = np.zeros(len(keys), bool)
            settled[won] = True
            left = left[~settled[left]]
            slot[left] = (slot[left] + 1) & self.mask

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * _U(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def get(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Values, and which keys there are."""
        slot = self._slot(keys)
        have = self.keys[slot]
        hit = have == keys
        values = np.where(hit, self.values[slot], np.float32(0))
        open_ = np.flatnonzero(~hit & (have != 0))
        at = slot[open_]
        while len(open_):
            at = (at + 1) & self.mask
            have = self.keys[at]
            same = have == keys[open_]
            values[open_[same]], hit[open_[same]] = self.values[at[same]], True
            go = ~same & (have != 0)
            open_, at = open_[go], at[go]
        return values, hit

    def log_p(self, keys: np.ndarray) -> np.ndarray:
        """Natural logs of the probability of each sequence's last byte."""
        d = self.depth
        value, hit = self.get(keys | (_U(d + 1) << _TAG))
        out = value.astype(np.float64)
        left = np.flatnonzero(~hit)
        while len(left):
            k = keys[left]
            context = k >> _U(8 * (self.depth + 1 - d))
            more, _ = self.get(context | (_U(128 + d) << _TAG))
            out[left] += more
            d -= 1
            if d < 0:
                out[left] -= np.log(256)
                break
            value, hit = self.get(((k >> _U(8 * (self.depth + 1 - d))) << _U(8)) | (k & _U(255)) | (_U(d + 1) << _TAG))
            out[left[hit]] += value[hit]
            left = left[~hit]
        return out


def learned_table(docs: DataFrame, depth: int = DEPTH) -> tuple[DataFrame, np.ndarray, np.ndarray]:
    """The table of all texts of docs: (key, v) of depths 1 and more, and keys and values of depth 0."""
    grams = written(gram_counts(docs, depth), "grams")
    recent = F.shiftrightunsigned("key", 8 * depth)
    parted = grams.withColumn("recent", recent)
    top = parted.groupBy("recent").applyInArrow(top_nodes(depth), "bit int, prefix long, zeros double, ones double, mixed double")
    sums = top.groupBy("bit", "prefix").agg(F.sum("zeros"), F.sum("ones"), F.sum("mixed")).collect()  # 255 rows at most
    roots = {}
    for bit, prefix, zeros, ones, below in sums:
        own = float(kt(np.asarray([zeros]), np.asarray([ones]))[0])
        roots[bit, prefix] = (float(np.exp(np.log(0.5) + own - (np.logaddexp(own, below) - np.log(2)))), zeros, ones)
    made = written(parted.groupBy("recent").applyInArrow(tabled(depth, roots), "key long, v float"), "table")
    # Depth 0: each byte's probability without context, from the roots alone.
    seen = [b for b in range(256) if all((bit, b >> (8 - bit)) in roots and roots[bit, b >> (8 - bit)][1 + ((b >> (7 - bit)) & 1)] > 0 for bit in range(8))]
    q0 = np.zeros(len(seen))
    for bit in range(8):
        q0 += np.log([(roots[bit, b >> (8 - bit)][1 + ((b >> (7 - bit)) & 1)] + 0.5) / (sum(roots[bit, b >> (8 - bit)][1:]) + 1.0) for b in seen]) if seen else 0
    k0 = np.asarray([b | (1 << 56) for b in seen] + [128 << 56], np.uint64)
    v0 = np.append(q0, rest(np.asarray([np.exp(q0).sum()]), np.asarray([len(seen) / 256]))[0] if seen else 0.0)
    return made, k0, v0.astype(np.float32)


def _collected(made: DataFrame, k0: np.ndarray, v0: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    got = made.toArrow()
    return np.concatenate((got.column("key").to_numpy().view(np.uint64), k0)), np.concatenate((got.column("v").to_numpy(), v0))


def learn(docs: DataFrame, depth: int = DEPTH) -> tuple[np.ndarray, np.ndarray, int]:
    """The table of all texts of docs on the driver: keys, values, depth."""
    return *_collected(*learned_table(docs, depth)), depth


def chunked(own: DataFrame) -> DataFrame:
    """own(doc_id, text) and the chunk of about CHUNK characters that each row is in."""

    def numbered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chunk, size = TaskContext.get().partitionId() << 32, 0
        for b in batches:
            of = []
            for text in b.column(1):
                if size >= CHUNK:
                    chunk, size = chunk + 1, 0
                of.append(chunk)
                size += len(text.as_py() or "")
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(of, pa.int64())], ["doc_id", "text", "chunk"])

    return own.mapInArrow(numbered, "doc_id long, text string, chunk long")


def asked(chunks: DataFrame, depth: int) -> DataFrame:
    """(chunk, key): the sequences that a chunk's texts hold, each at least once."""

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, found, pad = None, [], END * depth

        def out() -> pa.RecordBatch:
            keys = np.unique(np.concatenate(found))
            return pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), now, np.int64)), pa.array(keys.view(np.int64))], ["chunk", "key"])

        for b in batches:
            for text, chunk in zip(b.column(0), b.column(1).to_pylist(), strict=True):
                if found and (chunk != now or len(found) >= 4096):
                    whole = out()
                    found = [] if chunk != now else [whole.column(1).to_numpy().view(np.uint64)]
                    if chunk != now:
                        yield whole
                now = chunk
                found += [np.unique(k) for k in _steps(pad + stream(text.as_py())[1], depth)]
        if found:
            yield out()

    return chunks.select("text", "chunk").mapInArrow(made, "chunk long, key long")


def answers(keys: DataFrame, made: DataFrame, k0: np.ndarray, v0: np.ndarray, depth: int) -> DataFrame:
    """Each of keys(key), and the natural log of the probability of its last byte: what Table.log_p gives, by joins."""
    zero = keys.sparkSession.createDataFrame(list(zip(k0.view(np.int64).tolist(), v0.tolist(), strict=True)), "key long, v float")
    table, kind, key = made.unionByName(zero), F.shiftrightunsigned("key", 56), F.col("key")
    done, left = [], keys.distinct().withColumn("acc", F.lit(0.0))
    for d in range(depth, -1, -1):
        context = F.shiftrightunsigned(key, 8 * (depth + 1 - d))
        of = lambda tag, name: table.filter(kind == tag).select((key.bitwiseAND((1 << 56) - 1)).alias("_name"), F.col("v").alias(name))  # noqa: B023, E731
        name = F.shiftleft(context, 8).bitwiseOR(key.bitwiseAND(255))
        met = written(left.withColumn("_name", name).join(of(d + 1, "_v"), "_name", "left").drop("_name"), "met")
        done.append(met.filter("_v is not null").select("key", (F.col("acc") + F.col("_v")).alias("log_p")))
        left = met.filter("_v is null").withColumn("_name", context).join(of(128 + d, "_rest"), "_name", "left").select("key", (F.col("acc") + F.coalesce("_rest", F.lit(0.0))).alias("acc"))
    done.append(left.select("key", (F.col("acc") - float(np.log(256))).alias("log_p")))
    return reduce(DataFrame.unionByName, done)


class Answers:
    """What a chunk got for the sequences it asked for."""

    def __init__(self, keys: np.ndarray, values: np.ndarray) -> None:
        o = np.argsort(keys)
        self.keys, self.values = keys[o], values[o]

    def log_p(self, keys: np.ndarray) -> np.ndarray:
        return self.values[np.searchsorted(self.keys, keys)]


def word_counts(docs: DataFrame) -> DataFrame:
    """(word, n) over all texts, words as bytes; the end of each text counts as the empty word."""

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: Counter[bytes] = Counter()

        def out() -> Iterator[pa.RecordBatch]:
            w = list(found)
            for at in range(0, len(w), 50_000):
                part = w[at : at + 50_000]
                yield pa.RecordBatch.from_arrays([pa.array(part, pa.binary()), pa.array([found[x] for x in part], pa.int64())], ["word", "n"])

        for b in batches:
            for text in b.column(0):
                found.update(stream(text.as_py())[0])
                found[b""] += 1
                if len(found) > 400_000:
                    yield from out()
                    found.clear()
        yield from out()

    return docs.select("text").mapInArrow(counted, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))


def score(docs: DataFrame, learned: int = 7, held: int = 2, depth: int = DEPTH, max_entries: int = MAX_ENTRIES) -> DataFrame:
    """docs(doc_id, text, ...) -> doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, n_scored_bytes, bits_per_byte.

    Learns from the rows whose crc32(doc_id as text) mod `learned` is not `held`. One row for each row; null and empty texts are
    an end alone. Without training rows, words are all unknown and bytes equally likely. A table of up to `max_entries` entries is
    sent to every worker; beyond, chunks of texts ask for the sequences they hold, to the same scores.
    An empty table gives no rows; extra columns are ignored.
    """
    spark = docs.sparkSession
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    training = own.filter(crc_mod(F.col("doc_id"), learned) != held)
    counts = written(word_counts(training), "words")
    total, distinct = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    # Words from a count on, of which there are FREQUENT at most; octaves in sixteen steps, so that the driver sees a short histogram.
    octave = F.floor(16 * F.log2("n"))
    steps, least, number = sorted(((r[0], r[1]) for r in counts.groupBy(octave.alias("o")).count().collect()), reverse=True), None, 0
    for o, k in steps:
        number += k
        if number > FREQUENT:
            break
        least = o
    top = counts.filter(octave >= least if least is not None else F.lit(False)).toArrow()
    frequent = spark.sparkContext.broadcast(dict(zip(top.column("word").to_pylist(), top.column("n").to_pylist(), strict=True)))
    made, k0, v0 = learned_table(training, depth)
    all_ = float(total + distinct + 1)
    names = ["doc_id", "held_out", "n_tokens", "n_known", "base_score", "score", "n_scored_bytes", "rare"]
    rare_type = pa.list_(pa.struct([("word", pa.binary()), ("k", pa.int64())]))
    types = (pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.int64(), rare_type)

    def scored(part: pa.RecordBatch | pa.Table, lookup: Table | Answers, logs: dict[bytes, float]) -> pa.RecordBatch:
        out, texts, pad = [], [], END * depth
        for doc, text in zip(part.column("doc_id").to_pylist(), part.column("text"), strict=True):
            w, raw = stream(text.as_py())
            known, base, rare = 0, 0.0, []
            for x, k in Counter(w).items():
                v = logs.get(x)
                if v is None:
                    rare.append({"word": x, "k": k})
                else:
                    known += k
                    base += k * v
            if (v := logs.get(b"")) is None:
                base -= float(np.log10(all_))
            else:
                known, base = known + 1, base + v
            texts.append(pad + raw)
            out.append([doc, py_crc_mod(doc, learned) == held, len(w) + 1, known, base, 0.0, len(raw), rare])
        short = [i for i, t in enumerate(texts) if len(t) < STEP]
        # The places where two joined texts meet ask for sequences that no text holds, so that Answers takes one text at a time.
        alone = isinstance(lookup, Answers)
        for group in [*([[i] for i in short] if alone else _groups(short, texts)), *[[i] for i, t in enumerate(texts) if len(t) >= STEP]]:
            logp = np.concatenate([lookup.log_p(k) for k in _steps(b"".join(texts[i] for i in group), depth)])
            # Byte i of the joined text has its log at i - depth; the padding of every text but the first is left out.
            end = 0
            for i in group:
                begin, end = end, end + len(texts[i])
                out[i][5] = float(logp[begin : end - depth].sum()) / np.log(10)
        return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names)

    def word_logs() -> dict[bytes, float]:
        return {w: float(np.log10((n + 1) / all_)) for w, n in frequent.value.items()}

    schema = "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, score double, n_scored_bytes long, rare array<struct<word binary, k long>>"
    if made.count() <= max_entries:
        model = spark.sparkContext.broadcast(_collected(made, k0, v0))

        def by_table(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            lookup, logs = Table(*model.value, depth), word_logs()
            for b in batches:
                for at in range(0, b.num_rows, 200):
                    yield scored(b.slice(at, 200), lookup, logs)

        found = own.mapInArrow(by_table, schema)
    else:
        chunks = written(chunked(own), "chunks")
        wanted = written(asked(chunks, depth), "asked")
        got = wanted.join(answers(wanted.select("key"), made, k0, v0, depth), "key")

        def by_chunk(rows: pa.Table, given: pa.Table) -> pa.Table:
            if not rows.num_rows:
                return pa.table([pa.array([], t) for t in types], names)
            lookup = Answers(given.column("key").to_numpy().view(np.uint64), given.column("log_p").to_numpy())
            return pa.Table.from_batches([scored(rows, lookup, word_logs())])

        found = chunks.groupBy("chunk").cogroup(got.groupBy("chunk")).applyInArrow(by_chunk, schema)
    made = written(found.withColumn("_row", F.monotonically_increasing_id()), "scored")
    rare = made.select("_row", F.inline("rare")).join(counts, "word", "left")
    c = F.coalesce("n", F.lit(0))
    more = rare.groupBy("_row").agg(F.sum(F.when(c > 0, F.col("k")).otherwise(0)).alias("_known"), F.sum(F.col("k") * F.log10((c + 1) / F.lit(all_))).alias("_base"))
    bits = -F.col("score") * F.lit(float(np.log2(10))) / F.col("n_scored_bytes")
    return made.drop("rare").join(more, "_row", "left").select(
        "doc_id", "held_out", "n_tokens", (F.col("n_known") + F.coalesce("_known", F.lit(0))).alias("n_known"), F.lit(int(total)).cast("long").alias("train_tokens"),
        (F.col("base_score") + F.coalesce("_base", F.lit(0.0))).alias("base_score"), "score", "n_scored_bytes", bits.alias("bits_per_byte"),
    )


def _groups(indices: list[int], texts: list[bytes]) -> Iterator[list[int]]:
    group, size = [], 0
    for i in indices:
        group.append(i)
        size += len(texts[i])
        if size >= STEP:
            yield group
            group, size = [], 0
    if group:
        yield group
