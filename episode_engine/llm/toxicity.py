"""Toxicity by weak supervision.

Voters (a fixed lexicon, stems induced from labelled rows, patterns) vote or abstain. A generative label model,
fitted by expectation-maximisation on the counts of vote patterns of all learning rows, estimates how each voter
votes in either class and how far voters repeat one another; a linear classifier is trained on its posteriors.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_mod, py_crc_mod, written

#: Common insults, matched as whole words.
INSULTS = (
    "idiot idiots moron morons stupid loser losers pathetic worthless disgusting scum trash clown clowns imbecile dumb ugly filthy vermin bastard retard freak pig creep "
    "crétin connard abruti dummkopf arschloch vollidiot estúpido imbécil basura asqueroso"
).split()
#: Words of address.
ADDRESS = "you your you're u ur tu toi vous du dich dein ihr tú eres"
SHORTEST, LONGEST = 4, 8
#: Labelled rows that stems and the classifier are fitted on, taken in the order of a hash; of rows without a label it learns from all.
SAMPLE = 20_000
STEMS = 60
#: Standard errors that are taken off a stem's log ratio.
CHANCE = 2.2


def _words(text: str) -> list[str]:
    return re.findall(r"\w+", text.lower())


def _stems(text: str) -> Counter:
    found: Counter[str] = Counter()
    for w, n in Counter(_words(text)).items():
        for k in range(SHORTEST, min(LONGEST, len(w)) + 1):
            found[w[:k]] += n
    return found


def _count_stems(wanted: set[str] | None):
    """(stem, once, twice): in how many texts a stem begins a word at all, and twice or more."""

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        once: Counter[str] = Counter()
        twice: Counter[str] = Counter()
        for b in batches:
            for text in b.column(0):
                found = _stems(text.as_py() or "")
                names = list(found) if wanted is None else wanted.intersection(found)
                once.update(names)
                twice.update([x for x in names if found[x] > 1])
        names = list(once)
        yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array([once[x] for x in names], pa.int64()), pa.array([twice[x] for x in names], pa.int64())], ["stem", "once", "twice"])

    return made


def induce(sample: DataFrame, most: int = STEMS) -> list[tuple[str, int]]:
    """Stems of words that are surely more frequent in toxic texts of sample(text, toxic), and how often they must occur to tell."""
    spec = "stem string, once long, twice long"
    sizes = {r[0]: r[1] for r in sample.groupBy("toxic").count().collect()}
    p, n = sizes.get(1, 0), sizes.get(0, 0)
    least = max(4, 3 * p // 100)  # there are at most 42 times as many such stems as a toxic text has on average, however many texts there are
    counted = lambda label, wanted: sample.filter(F.col("toxic") == label).select("text").mapInArrow(_count_stems(wanted), spec).groupBy("stem").agg(F.sum("once").alias("once"), F.sum("twice").alias("twice"))
    often = counted(1, None).filter(F.col("once") >= least).orderBy(F.desc("once"), "stem").collect()
    if not often:
        return []
    rare = {r[0]: r[1:] for r in counted(0, {r[0] for r in often}).collect()}
    found = []
    for stem, once, twice in often:
        a, b = rare.get(stem, (0, 0))
        # The log ratio of the shares, less what chance may add to it; the better of "at all" and "twice or more".
        sure = lambda x, y: np.log((x + 0.5) / (p + 1)) - np.log((y + 0.5) / (n + 1)) - CHANCE * np.sqrt(1 / (x + 0.5) + 1 / (y + 0.5)) if x >= least else -9.0
        value, times = max((sure(once, a), 1), (sure(twice, b), 2))
        if value >= 1:
            found.append((-value, len(stem), stem, times))
    chosen: list[tuple[str, int]] = []
    for _, _, stem, times in sorted(found):
        if not any(stem.startswith(c) or c.startswith(stem) for c, _ in chosen):
            chosen.append((stem, times))
    return chosen[:most]


class Voters:
    """Counts, votes and features of a text."""

    def __init__(self, stems: list[tuple[str, int]]) -> None:
        import ahocorasick

        self.times, self.size = np.asarray([n for _, n in stems], dtype=float), len(INSULTS) + len(stems)
        self.search = ahocorasick.Automaton()
        entries: dict[str, list[tuple[int, bool]]] = {}
        for i, w in enumerate([*INSULTS, *[x for x, _ in stems]]):
            entries.setdefault(w, []).append((i, i < len(INSULTS)))
        for w, found in entries.items():
            self.search.add_word(w, (len(w), found))
        self.search.make_automaton()
        self.address = re.compile(rf"\b(?:{'|'.join(map(re.escape, ADDRESS.split()))})\b(?:\W+\w+){{0,3}}?\W+(?:{'|'.join(INSULTS)})\b")

    def look(self, text: str | None) -> tuple[list[int], list[float]]:
        raw = text or ""
        t = raw.lower()
        counts = np.zeros(self.size)
        for end, (n, found) in self.search.iter(t):
            before = end - n
            if before >= 0 and (t[before].isalnum() or t[before] == "_"):
                continue
            whole = end + 1 == len(t) or not (t[end + 1].isalnum() or t[end + 1] == "_")
            for i, need in found:
                if whole or not need:
                    counts[i] += 1
        k = len(INSULTS)
        fixed, stem = counts[:k].sum(), counts[k:].sum()
        n_words = t.count(" ") + t.count("\n") + 1
        share = (fixed + stem) / n_words
        shout = len(raw) >= 20 and raw.isupper()
        votes = [
            int(fixed >= 1),
            int((counts[:k] > 0).sum() >= 2),
            int((counts[k:] >= self.times).any()),
            1 if share >= 0.005 else (-1 if share == 0 else 0),
            -1 if fixed + stem == 0 else 0,
            int(shout),
            int(bool(fixed and self.address.search(t))),
        ]
        x = [*np.log1p(counts), np.log1p(fixed), np.log1p(stem), float((counts > 0).sum()), min(10.0, 100 * share), np.log1p(n_words) / 10, *[float(v) for v in votes]]
        return votes, [float(v) for v in x]


def label_model(patterns: list[tuple[tuple[int, ...], int | None, int]], rounds: int = 40) -> tuple[np.ndarray, list[int | None]]:
    """Posterior of class 1 for each (votes, known label or None, rows).

    Rows with a label keep it. For the others voters count by their log likelihood ratio, divided by one plus the
    correlations that are left with other voters inside the classes, so that voters that repeat each other count once.
    """
    votes = np.asarray([p[0] for p in patterns], dtype=int).reshape(len(patterns), -1)
    rows = np.asarray([p[2] for p in patterns], dtype=float)
    known = [p[1] for p in patterns]
    fixed = np.asarray([-1.0 if y is None else float(y) for y in known])
    k = votes.shape[1]
    hot = np.stack([votes == v for v in (-1, 0, 1)], axis=2).astype(float)
    table = np.tile(np.asarray([[0.2, 0.4, 0.4], [0.5, 0.48, 0.02]])[:, None, :], (1, k, 1))
    prior, share = 0.1, np.ones(k)
    q, odds = np.full(len(rows), prior), np.zeros(len(rows))
    for r in range(rounds):
        ratio = (hot * (np.log(table[0]) - np.log(table[1]))[None]).sum(axis=2)
        odds = np.log(prior / (1 - prior)) + (ratio * share).sum(axis=1)
        q = np.where(fixed >= 0, fixed, 1 / (1 + np.exp(-np.clip(odds, -30, 30))))
        weights = [rows * q, rows * (1 - q)]
        prior = float(np.clip((weights[0].sum() + 1) / (rows.sum() + 10), 0.001, 0.5))
        for c, w in enumerate(weights):
            table[c] = ((hot * w[:, None, None]).sum(axis=0) + 0.5) / (w.sum() + 1.5)
        if r >= 5:
            total = np.zeros((k, k))
            for w in weights:
                d = votes - (votes * w[:, None]).sum(axis=0) / max(w.sum(), 1e-9)
                cov = (d * w[:, None]).T @ d
                s = np.sqrt(np.maximum(np.diag(cov), 1e-9))
                total += w.sum() * np.abs(cov / s[:, None] / s[None, :])
            corr = total / max(rows.sum(), 1e-9)
            share = 1 / np.maximum(1.0, corr.sum(axis=1))
    if rows[fixed == 1].sum() >= 10 and rows[fixed == 0].sum() >= 10:  # the scale of the odds, from rows with labels
        has = fixed >= 0
        a, b = fit_linear(odds[has, None], fixed[has], 1e-3, rows=rows[has])
        q = np.where(has, fixed, 1 / (1 + np.exp(-np.clip(max(a, 0.0) * odds + b, -30, 30))))
    return q, known


def _sums(x: np.ndarray, q: np.ndarray, w: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """What a Newton step needs of rows: the gradient and the curvature of their log likelihood at w."""
    p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
    return x.T @ (rows * (q - p)), (x * (rows * p * (1 - p))[:, None]).T @ x


def fit_all(learned: DataFrame, posterior: dict[tuple[tuple[int, ...], int | None], float], ridge: float = 1.0, steps: int = 25) -> np.ndarray:
    """fit_linear over every row of learned(x, votes, toxic), a pass for each Newton step.

    A task sends one sum a step, whose size is that of the features; rows never come to the driver.
    """
    first = learned.select(F.size("x")).first()
    w = np.zeros(first[0] + 1)
    keep = np.full(len(w), ridge)
    keep[-1] = 1e-3

    def summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = [np.zeros(len(w)), np.zeros((len(w), len(w)))]
        for b in batches:
            if b.num_rows:
                values = b.column("x").flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1).astype(float)
                y = np.asarray([posterior[tuple(v), t] for v, t in zip(b.column("votes").to_pylist(), b.column("toxic").to_pylist(), strict=True)])
                for k, part in enumerate(_sums(np.hstack([values, np.ones((b.num_rows, 1))]), y, w, np.ones(b.num_rows))):
                    total[k] += part
        yield pa.RecordBatch.from_arrays([pa.array([total[0].tolist()]), pa.array([total[1].ravel().tolist()])], ["gradient", "curvature"])

    for _ in range(steps):
        gradient, curvature = np.zeros(len(w)), np.zeros((len(w), len(w)))
        sums = learned.mapInArrow(summed, "gradient array<double>, curvature array<double>").toArrow()
        for part in sums.to_batches():
            gradient += part.column(0).flatten().to_numpy().reshape(-1, len(w)).sum(axis=0)
            curvature += part.column(1).flatten().to_numpy().reshape(-1, len(w), len(w)).sum(axis=0)
        step = np.linalg.solve(curvature + np.diag(keep + 1e-6), gradient - keep * w)
        w = w + np.clip(step, -4, 4)
        if np.abs(step).max() < 1e-4:
            break
    return w


def fit_linear(x: np.ndarray, q: np.ndarray, ridge: float = 1.0, steps: int = 25, rows: np.ndarray | None = None) -> np.ndarray:
    """Logistic regression on soft labels by Newton's method; the last weight is the constant."""
    x = np.hstack([x, np.ones((len(x), 1))])
    w = np.zeros(x.shape[1])
    keep, rows = np.full(len(w), ridge), np.ones(len(x)) if rows is None else rows
    keep[-1] = 1e-3
    for _ in range(steps):
        gradient, curvature = _sums(x, q, w, rows)
        step = np.linalg.solve(curvature + np.diag(keep + 1e-6), gradient - keep * w)
        w += np.clip(step, -4, 4)
        if np.abs(step).max() < 1e-4:
            break
    return w


def toxicity(docs: DataFrame, labels: DataFrame, mod: int = 3, held: int = 1, threshold: float = 0.7, sample: int = SAMPLE) -> DataFrame:
    """docs(doc_id, text, ...), labels(doc_id, toxic, ...) -> doc_id, held_out, score, predicted: a row for each row.

    Whole texts are scored, and nothing else of a row. It learns from rows whose crc32(doc_id as text) mod `mod` is not
    `held` only: labels of at most `sample` of them, in the order of a hash, and all others without a label. Null texts are empty; labels that are neither
    0 nor 1 are left out, and of several labels of one document the highest holds. Without labels, the label model stands
    on its voters alone. An empty table gives no rows; extra columns are ignored.
    """
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    learning = crc_mod(F.col("doc_id"), mod) != held
    known = labels.filter(F.col("toxic").isin(0, 1) & learning).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("toxic").cast("int").alias("toxic"))
    known = written(known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample), "labels")  # bounded, so that it may be broadcast
    stems = induce(written(own.join(F.broadcast(known), "doc_id").select("text", "toxic"), "labelled"))

    def looked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        voters = Voters(stems)
        for b in batches:
            for at in range(0, b.num_rows, 1000):
                part = b.slice(at, 1000)
                v, x = zip(*[voters.look(t.as_py()) for t in part.column(1)], strict=True)
                ids = part.column(0)
                held_out = [i is not None and py_crc_mod(i, mod) == held for i in ids.to_pylist()]
                yield pa.RecordBatch.from_arrays([ids, pa.array(held_out), pa.array(list(v), pa.list_(pa.int32())), pa.array(list(x), pa.list_(pa.float32()))], ["doc_id", "held_out", "votes", "x"])

    seen = written(own.mapInArrow(looked, "doc_id long, held_out boolean, votes array<int>, x array<float>"), "votes")
    learned = seen.filter(~F.col("held_out")).join(F.broadcast(known), "doc_id", "left")
    # At most 2 ** 6 * 3 patterns and three states of the label.
    counts = learned.groupBy("votes", "toxic").count().collect()
    if not counts:
        weights = np.zeros(1)
    else:
        q, _ = label_model([(tuple(r[0]), r[1], r[2]) for r in counts])
        posterior = {(tuple(r[0]), r[1]): v for r, v in zip(counts, q.tolist(), strict=True)}
        weights = fit_all(learned.select("x", "votes", "toxic"), posterior)

    def scored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = np.asarray(b.column("x").to_pylist(), dtype=float).reshape(b.num_rows, -1)
            s = 1 / (1 + np.exp(-np.clip(x @ weights[:-1] + weights[-1], -30, 30)))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("held_out"), pa.array(s), pa.array((s >= threshold).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return seen.select("doc_id", "held_out", "x").mapInArrow(scored, "doc_id long, held_out boolean, score double, predicted int")
