"""Toxicity: a support vector machine over a normalised gap-weighted subsequence kernel, with Nyström landmarks.

A text is a bag of strings, and is as toxic as the most toxic of them. Strings are compared by the kernel alone: nothing is stripped from
them, and words of any length count.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xlsql.session import bound_batches

#: Characters of a subsequence, the characters it may span, and the weight of each character spanned.
LENGTH, SPAN, DECAY = 3, 5, 0.6
LANDMARKS = 192
#: Documents of each class that the machine is fitted on, the first by a hash of their ids, and bytes of their whole texts.
SAMPLE_DOCS, SAMPLE_BYTES = 1500, 4 << 20
#: Longer strings are compared as overlapping pieces of this many characters.
LONGEST = 24
#: Strings whose margins a worker remembers, and how many are compared together.
REMEMBERED, AT_ONCE = 250_000, 4096
#: Neighbours of at most this many characters may be one string that spaces cut.
SHORT = 3
#: Characters of a word's beginning that can be a stem.
STEM = 5
#: Most rounds of choosing the most toxic string of each text and fitting anew, and the weight of a string that only told a text from the start.
ROUNDS, TELLING = 6, 0.25
#: Neighbours of at most ``SHORT`` characters.
SHORT_RUN = re.compile(rf"(?<!\S)\S{{1,{SHORT}}}(?:\s+\S{{1,{SHORT}}})+(?!\S)").findall
OFFSETS = [(a, b) for a in range(1, SPAN - 1) for b in range(a + 1, SPAN)]
WEIGHTS = np.array([DECAY ** (LENGTH + k) for k in range(4)])
MIX = np.uint64(0x9E3779B97F4A7C15)


def strings_of(text: str | None, disguised: bool = True) -> set[str]:
    """The bag of a whole text: its lower-case words between spaces, and what may be words in disguise.

    Those are every other character of a word (one stands between all letters), neighbours of at most ``SHORT`` characters put together, and
    runs of single characters put together. The beginnings of words longer than ``STEM`` count as strings too, behind the mark of a word's begin.
    """
    plain = text.lower() if text else ""
    out = set(plain.split())
    long = [w for w in out if len(w) > STEM]
    out.update(["\x02" + w[:STEM] for w in long])
    if not disguised:
        return out
    out.update([w[::2] for w in long])
    for run in SHORT_RUN(plain):
        words = run.split()
        out.update([a + b for a, b in zip(words, words[1:]) if len(a) + len(b) > SHORT])
        single = "".join([w if len(w) == 1 else " " for w in words])
        out.update([w for w in single.split(" ") if len(w) > 3])
    return out


def marked(word: str) -> str:
    """A word between the marks of its ends; a beginning has its mark already."""
    return word if word[:1] == "\x02" else f"\x02{word}\x03"


def chunks_of(words: list[str]) -> tuple[list[str], np.ndarray]:
    """Words between marks of their ends, long ones as overlapping pieces of ``LONGEST`` characters, and the word each comes from."""
    out = [w if w[:1] == "\x02" else f"\x02{w}\x03" for w in words]
    if max(map(len, out), default=0) <= LONGEST:
        return out, np.arange(len(out))
    parts = [[w] if len(w) <= LONGEST else [w[k : k + LONGEST] for k in range(0, len(w) - SPAN, LONGEST - 2 * SPAN)] for w in out]
    return [x for some in parts for x in some], np.repeat(np.arange(len(out)), [len(x) for x in parts])


def subsequences(strings: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(string, code, weight) of every distinct subsequence of ``LENGTH`` characters of each string: the sum of its occurrences' weights.

    An occurrence counts ``DECAY`` to the power of the characters it spans, ``SPAN`` at most. String, 46 bits of a hash of the three
    characters and the span make up one number, so that one sort brings equal subsequences together. Takes at most 32,768 strings.
    """
    if not strings:
        return np.zeros(0, int), np.zeros(0, "i8"), np.zeros(0)
    width = max(map(len, strings))
    flat = np.frombuffer("".join([w.ljust(width + SPAN, "\0") for w in strings]).encode("utf-32-le", "surrogatepass"), "<u4").reshape(len(strings), -1).astype("u8")
    first, number = flat[:, :width], (np.arange(len(strings), dtype="u8") << np.uint64(48))[:, None]
    keys = []
    for a, b in OFFSETS:
        last = flat[:, b : width + b]
        h = (first * MIX ^ flat[:, a : width + a]) * MIX
        h = ((h ^ h >> np.uint64(29) ^ last) * MIX) >> np.uint64(18)
        keys.append((number | h << np.uint64(2) | np.uint64(b - LENGTH + 1))[last != 0])
    keys = np.sort(np.concatenate(keys))
    if not len(keys):
        return np.zeros(0, int), np.zeros(0, "i8"), np.zeros(0)
    start = np.flatnonzero(np.concatenate([[True], keys[1:] >> np.uint64(2) != keys[:-1] >> np.uint64(2)]))
    weight = np.add.reduceat(WEIGHTS[(keys & np.uint64(3)).astype("i8")], start)
    keys = keys[start]
    return (keys >> np.uint64(48)).astype("i8"), (keys >> np.uint64(2) & np.uint64((1 << 46) - 1)).astype("i8"), weight


@dataclass
class Machine:
    """Landmark strings as sorted subsequence codes with their normalised weights, the machine's weight of each landmark, and its calibration."""

    landmarks: list[str]
    codes: np.ndarray
    table: np.ndarray
    direction: np.ndarray
    bias: float
    slope: float
    shift: float

    @classmethod
    def of(cls, landmarks: list[str]) -> Machine:
        """No direction yet. Landmarks must not be longer than a piece."""
        at, code, weight = subsequences([marked(z) for z in landmarks])
        codes, i = np.unique(code, return_inverse=True)
        table = np.zeros((len(codes), len(landmarks)))
        np.add.at(table, (i, at), weight)
        return cls(landmarks, codes, table / np.maximum(np.sqrt((table**2).sum(0)), 1e-300), np.zeros(len(landmarks)), 0.0, 1.0, 0.0)

    def __post_init__(self):
        self.known = np.zeros(1 << 16, bool)
        self.known[self.codes & 0xFFFF] = True

    def _hits(self, parts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(part, place among the codes, weight as a share of the part's norm) of the subsequences that a landmark has."""
        at, code, weight = subsequences(parts)
        if not len(at) or not len(self.codes):
            return np.zeros(0, int), np.zeros(0, int), np.zeros(0)
        norm = np.sqrt(np.bincount(at, weight**2))
        some = np.flatnonzero(self.known[code & 0xFFFF])
        i = np.minimum(np.searchsorted(self.codes, code[some]), len(self.codes) - 1)
        same = self.codes[i] == code[some]
        some, i = some[same], i[same]
        return at[some], i, weight[some] / norm[at[some]]

    def kernel(self, words: list[str]) -> np.ndarray:
        """Normalised kernel, 0 to 1, of each word (of its first piece, if it is long) with each landmark."""
        out = np.zeros((len(words), len(self.landmarks)))
        for k in range(0, len(words), AT_ONCE):
            at, i, share = self._hits([marked(w)[:LONGEST] for w in words[k : k + AT_ONCE]])
            for j in range(0, len(at), 1 << 17):
                np.add.at(out, k + at[j : j + (1 << 17)], self.table[i[j : j + (1 << 17)]] * share[j : j + (1 << 17), None])
        return out

    def margins(self, words: list[str]) -> np.ndarray:
        """Margin of each word; of a long one that of its best piece. The landmarks' weights are added up for each subsequence beforehand."""
        out, worth = np.full(len(words), -np.inf), self.table @ self.direction
        parts, owner = chunks_of(words)
        for k in range(0, len(parts), AT_ONCE):
            at, i, share = self._hits(parts[k : k + AT_ONCE])
            value = np.bincount(at, share * worth[i], len(parts[k : k + AT_ONCE])) if len(at) else np.zeros(len(parts[k : k + AT_ONCE]))
            np.maximum.at(out, owner[k : k + AT_ONCE], value + self.bias)
        return out

    def score(self, margin: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * margin + self.shift, -30, 30)))


class Scorer:
    """Margin of whole texts: the greatest of their strings' margins, which are remembered up to ``REMEMBERED`` strings; an empty text has the bias."""

    def __init__(self, machine: Machine):
        self.machine, self.memory = machine, {}

    def learn(self, strings: Iterable[str]) -> None:
        new = [w for w in strings if w not in self.memory]
        for k in range(0, len(new), AT_ONCE):
            part = new[k : k + AT_ONCE]
            self.memory.update(zip(part, self.machine.margins(part).tolist()))

    def margins(self, texts: list[str | None]) -> np.ndarray:
        bags = [strings_of(t) for t in texts]
        every = set().union(*bags)
        if len(self.memory) + len(every) > REMEMBERED:
            self.memory = {}
        if len(every) <= REMEMBERED:
            self.learn(every)
        out = np.full(len(bags), self.machine.bias)
        for k, bag in enumerate(bags):
            if len(every) > REMEMBERED:
                # a batch of this many strings is one very long text or a few: each is taken in turn
                held = list(bag)
                best = max((float(self.machine.margins(held[i : i + AT_ONCE]).max()) for i in range(0, len(held), AT_ONCE)), default=self.machine.bias)
            else:
                best = max(map(self.memory.__getitem__, bag), default=self.machine.bias)
            out[k] = max(best, self.machine.bias)
        return out


def _candidates(bags: list[set[str]], labels: np.ndarray) -> dict[str, float]:
    """Strings that stand in texts of label 1 more often than in others beyond chance, and how much they tell: a log-ratio of shares, times the share."""
    toxic, clean = Counter(), Counter()
    for bag, label in zip(bags, labels):
        (toxic if label else clean).update(w for w in bag if len(w) + 2 <= LONGEST)
    n, m = max(1, int(labels.sum())), max(1, int((~labels).sum()))
    worth, often = {}, {w: c for w, c in toxic.items() if c > 2}
    # of so many strings one would come this far by chance
    chance = 2 * np.log(max(2, len(often)))
    for w, c in often.items():
        p, q, both = c / n, clean[w] / m, (c + clean[w]) / (n + m)
        if p > 4 * q and (p - q) ** 2 > chance * both * (1 - both + 1e-9) * (1 / n + 1 / m):
            worth[w] = p * np.log((p + 0.5 / n) / (q + 0.5 / m))
    return worth


def _svm(x: np.ndarray, y: np.ndarray, weight: np.ndarray, rounds: int = 800, ridge: float = 1e-4) -> tuple[np.ndarray, float]:
    """Linear machine with squared hinge loss, by accelerated gradient descent."""
    z = np.hstack([x, np.ones((len(x), 1))])
    step = 1 / (2 * np.linalg.eigvalsh(z.T @ (z * weight[:, None]))[-1] / weight.sum() + ridge)
    w = v = np.zeros(z.shape[1])
    for k in range(rounds):
        slack = np.maximum(0, 1 - y * (z @ v)) * weight
        grad = -2 * z.T @ (slack * y) / weight.sum() + ridge * np.r_[v[:-1], 0]
        w, v = v - step * grad, v - step * grad + k / (k + 3) * (v - step * grad - w)
    return w[:-1], float(w[-1])


def train(texts: list[str], labels: list[int], landmarks: int = LANDMARKS) -> Machine:
    """Fit on labelled texts.

    Landmarks are training strings: first those that tell the classes apart, then, round by round, the strings of clean texts that the machine
    takes for toxic. Each round maps the most toxic string of every text to its Nyström features k(x, landmarks) k(landmarks)^(-1/2), fits
    the machine to them, and lets it choose strings anew. At last the margins of the texts are calibrated by a sigmoid.
    """
    y = np.array(labels, int) == 1
    bags = [strings_of(t) for t in texts]
    plain = [strings_of(t, False) for t in texts]
    worth = _candidates(plain, y)
    if not worth:
        share = float(np.clip(y.mean(), 0.01, 0.49)) if len(y) else 0.01
        machine = Machine.of([])
        machine.slope, machine.shift = 0.0, float(np.log(share / (1 - share)))
        return machine
    chosen = sorted(worth, key=lambda w: (-worth[w], w))[: landmarks // 2]
    best = [max(bag, key=lambda w: (worth.get(w, -1.0), w), default="") for bag in plain]
    # a text of label 1 without any string that tells it from others teaches nothing about strings
    told = np.array([not label or w in worth for w, label in zip(best, y)])
    telling = Counter(w for bag, label in zip(plain, y) if label for w in bag & worth.keys())
    del plain
    every = sorted(set().union(*bags))
    machine, margins, against = Machine.of(chosen), {}, Counter()
    for turn in range(ROUNDS):
        own = machine.kernel(machine.landmarks)
        values, vectors = np.linalg.eigh((own + own.T) / 2)
        root = vectors / np.sqrt(np.maximum(values, 1e-3)) @ vectors.T
        # the most toxic string of each text told, and all that told it from the start
        toxic = {w: TELLING * c for w, c in telling.items()}
        for w, label, t in zip(best, y, told):
            if label and t:
                toxic[w] = toxic.get(w, 0.0) + 1
        # what is toxic stays so with a character put in or behind it
        seen = [(w, True) for w in toxic]
        seen += [(v, True) for w, label in seen if len(w) > 3 and w[0] != "\x02" for v in (w[: len(w) // 2] + "\x04" + w[len(w) // 2 :], w + "\x04", w[:1] + "\x04" + w[1:])]
        # every string that a clean text was taken for in any round stays a counterexample
        against.update(w for w, label in zip(best, y) if not label)
        times = np.array([toxic.get(w, 1.0) for w, _ in seen] + list(against.values()), float)
        seen += [(w, False) for w in against]
        mark = np.array([label for _, label in seen])
        balance = np.where(mark, 0.5 / max(1, times[mark].sum()), 0.5 / max(1, times[~mark].sum())) * times
        direction, machine.bias = _svm(machine.kernel([w for w, _ in seen]) @ root, np.where(mark, 1.0, -1.0), balance)
        machine.direction = root @ direction
        margins = dict(zip(every, machine.margins(every).tolist()))
        best = [max(bag, key=lambda w: (margins[w], w), default="") for bag in bags]
        told = np.array([not label or margins.get(w, -1) > 0 for w, label in zip(best, y)])
        if not any(margins.get(w, -1) > 0 for w, label in zip(best, y) if not label and w not in against):
            break
        if turn + 1 < ROUNDS:
            wrong = Counter(w for w, label in zip(best, y) if not label and margins.get(w, -1) > -0.5 and 3 < len(w) < LONGEST - 1)
            more = [w for w, _ in sorted(wrong.items(), key=lambda x: (-x[1], -margins[x[0]], x[0])) if w not in set(machine.landmarks)]
            added = more[: (landmarks - len(machine.landmarks)) // (ROUNDS - 1 - turn)]
            machine = Machine.of([*machine.landmarks, *added]) if added else machine
    margin, slope, shift = np.array([max(margins.get(w, machine.bias), machine.bias) for w in best]), 2.0, 0.0
    goal = np.where(y, (y.sum() + 1) / (y.sum() + 2), 1 / ((~y).sum() + 2))
    for _ in range(200):  # Platt's sigmoid by Newton steps
        p = 1 / (1 + np.exp(-np.clip(slope * margin + shift, -30, 30)))
        g = np.array([(margin * (p - goal)).sum() + 1e-2 * (slope - 2), (p - goal).sum()])
        s = p * (1 - p) + 1e-6
        h = np.array([[(margin**2 * s).sum() + 1e-2, (margin * s).sum()], [(margin * s).sum(), s.sum()]])
        d = np.linalg.solve(h, g)
        slope, shift = slope - np.clip(d[0], -1, 1), shift - np.clip(d[1], -1, 1)
        if np.abs(d).max() < 1e-9:
            break
    machine.slope, machine.shift = float(max(slope, 1e-3)), float(shift)
    return machine


def fit(labelled: DataFrame) -> Machine:
    """Fit on what ``labelled_rows`` has chosen. Null texts teach nothing."""
    rows = sorted((r["toxic"], r["text"]) for r in labelled.where(F.col("text").isNotNull()).select("toxic", "text").collect())
    return train([t for _, t in rows], [c for c, _ in rows])


def labelled_rows(docs: DataFrame, labels: DataFrame, per_class: int = SAMPLE_DOCS, most_bytes: int = SAMPLE_BYTES, doc_id: str = "doc_id", label: str = "toxic") -> DataFrame:
    """text, toxic of at most ``per_class`` labelled documents of each class and at most ``most_bytes`` of their whole texts, the first by a hash of their ids.

    Ids are chosen before any text is read; their number is bounded, so they are sent to every task. A document labelled both ways teaches
    nothing; of rows that repeat a doc_id the least text counts.
    """
    known = labels.where(F.col(label).isin(0, 1)).groupBy(F.col(doc_id).alias("doc_id")).agg(F.min(label).cast("int").alias("toxic"), F.max(label).cast("int").alias("other"))
    known = known.where("toxic = other and doc_id is not null").select("doc_id", "toxic", F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)).alias("place"))
    sizes = {r["toxic"]: r["count"] for r in known.groupBy("toxic").count().collect()}
    share = lambda c: int(min(1.0, 1.2 * per_class / max(1, sizes.get(c, 0))) * (1 << 30))
    near = known.where(F.col("place") < F.when(F.col("toxic") == 1, share(1)).otherwise(share(0)))
    held = docs.select(F.col(doc_id).alias("doc_id"), F.col("text").alias("text")).where("text is not null").join(F.broadcast(near), "doc_id")
    held = held.groupBy("doc_id", "toxic", "place").agg(F.min("text").alias("text"))
    # at most about 1.2 times per_class rows of each class
    found = held.select("toxic", "place", "doc_id", F.octet_length("text").alias("bytes")).collect()
    kept, count, total = [], Counter(), Counter()
    for r in sorted(found, key=lambda r: (r["place"], r["doc_id"])):
        c = r["toxic"]
        if count[c] < per_class and total[c] + r["bytes"] <= most_bytes:
            kept.append((r["doc_id"], c))
            count[c] += 1
        total[c] += r["bytes"]
    ids = docs.sparkSession.createDataFrame(sorted(set(kept)), known.select("doc_id", "toxic").schema)
    return held.drop("toxic", "place").join(F.broadcast(ids), "doc_id").select("text", "toxic")


def with_toxicity(docs: DataFrame, machine: Machine, text: str = "text", out: str = "toxicity") -> DataFrame:
    """Add a struct column ``out``: score (0 to 1), margin.

    Every string of the whole text is compared with the landmarks; gaps and inserted characters lower the kernel but do not break it. Null and
    empty texts have no string and get the machine's score of nothing. Rows and other columns stay, but a column named as ``out`` is replaced.
    """
    bound_batches(docs.sparkSession)

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        scorer = Scorer(machine)
        for batch in batches:
            margin = scorer.margins(list(batch))
            yield pd.DataFrame({"score": machine.score(margin), "margin": margin})

    return docs.withColumn(out, F.pandas_udf(run, "score double, margin double")(F.col(text)))
