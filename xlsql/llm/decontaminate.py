"""Benchmark decontamination: rare seeds counted in stretches, then Smith-Waterman alignment of words."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterable, Iterator
from itertools import repeat

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xlsql.llm.columns import fresh
from xlsql.session import bound_batches

#: Seeds are single words, for an edited copy at ``SIMILARITY`` may keep no two of an item's words side by side. Of each item the commonest
#: words are no seeds, up to this share of the words that a leak must match; what is left of that number must then be hit (so no leak is lost).
SPARED = 0.7
#: Blocks of text that hold any alignment of an item's length class; counters of hits, and words of the stretches found, held at once.
BLOCKS, COUNTERS, STRETCHED = 5, 1 << 22, 1 << 20
MATCH, MISMATCH, GAP = 2, -1, -1
#: Share of the item's own score that a leaked copy reaches.
SIMILARITY = 0.5
#: Bytes of benchmark texts that may be sent to every task (a worker's index takes about twenty times as much); more are handled slice by slice.
SLICE_BYTES = 4 << 20
WORD = re.compile(r"\w+").findall


def words_of(text: str | None) -> list[str]:
    return WORD(text.lower()) if text else []


def smith_waterman(a: np.ndarray, b: np.ndarray) -> int:
    """Best local alignment score of two sequences of word numbers; rows are swept with vectorised gaps (linear cost)."""
    if not len(a) or not len(b):
        return 0
    best, above, ramp = 0, np.zeros(len(b) + 1, "i8"), GAP * np.arange(len(b) + 1)
    for x in a:
        row = np.zeros(len(b) + 1, "i8")
        np.maximum(above[:-1] + np.where(b == x, MATCH, MISMATCH), above[1:] + GAP, out=row[1:])
        np.maximum(row, 0, out=row)
        # a gap along the row: best earlier value less its distance
        row = np.maximum.accumulate(row - ramp) + ramp
        above = row
        best = max(best, int(row.max()))
    return best


class Plan:
    """Seeds of the items of one length class: where alignments of at most ``span`` words must have ``need`` hits of an item's seeds."""

    def __init__(self, index: Index, members: list[int], goals: list[int], span: int):
        self.members, self.goals = members, goals
        self.block = -(-span // (BLOCKS - 1))
        pairs, need = [], []
        for k, (item, goal) in enumerate(zip((index.coded[m] for m in members), goals)):
            matches = -(-goal // MATCH)
            words, times = np.unique(item, return_counts=True)
            order = np.argsort(-index.frequency[words], kind="stable")
            spared = np.cumsum(times[order]) <= matches * SPARED
            need.append(matches - int(times[order][spared].sum()))
            pairs.append((words[order][~spared], k))
        at = np.concatenate([w for w, _ in pairs])
        order = np.argsort(at, kind="stable")
        self.owner = np.concatenate([np.full(len(w), k) for w, k in pairs])[order]
        self.start = np.searchsorted(at[order], np.arange(len(index.number) + 1))
        self.times = np.diff(self.start)
        self.need = np.array(need)
        self.goal, self.width = np.array(goals), len(index.number) + 1
        # member and word in one number, of all words of the members
        self.held = np.unique(np.concatenate([k * self.width + np.unique(index.coded[m]) for k, m in enumerate(members)]))
        self.table = np.zeros(len(members) * self.width if len(members) * self.width <= COUNTERS else 0, bool)
        if len(self.table):
            self.table[self.held] = True

    def _holds(self, member: np.ndarray, word: np.ndarray) -> np.ndarray:
        """Whether each member has the word beside it."""
        key = member * self.width + word
        return self.table[key] if len(self.table) else self.held[np.minimum(np.searchsorted(self.held, key), len(self.held) - 1)] == key

    def candidates(self, text: np.ndarray, place: np.ndarray, word: np.ndarray, size: np.ndarray) -> Iterator[tuple[int, int, int, int]]:
        """(text, member, first word, end word) of the stretches in which some sum of matches and mismatches reaches the member's goal.

        Such a sum is greatest from one of the member's words to another, so only these are laid out, those of all stretches as one sequence;
        from one stretch to the next it falls by more than it can rise within.
        """
        texts, members, first, end = self.stretches(text, place, word, size)
        begins = np.cumsum(size) - size
        at = begins[text] + place
        i, j = np.searchsorted(at, begins[texts] + first), np.searchsorted(at, begins[texts] + end)
        groups = np.cumsum(j - i) // STRETCHED
        edges = np.flatnonzero(np.diff(groups, prepend=-1, append=-1))
        for g, h in zip(edges[:-1], edges[1:]):
            n, k = (j - i)[g:h], members[g:h]
            which = np.repeat(np.arange(len(n)), n)
            spot = np.arange(len(which)) + np.repeat(i[g:h] - np.cumsum(n) + n, n)
            own = self._holds(k[which], word[spot])
            which, where = which[own], place[spot[own]]
            if not len(which):
                continue
            fall = which * ((MATCH - MISMATCH) * (len(which) + 1) - MISMATCH * (int(size.max()) + 1))
            upto = (MATCH - MISMATCH) * np.arange(1, len(which) + 1) + MISMATCH * (where + 1) - fall
            reached = upto - np.minimum.accumulate(upto - MATCH) >= self.goal[k[which]]
            for x in (g + np.unique(which[reached])).tolist():
                yield int(texts[x]), int(members[x]), int(first[x]), int(end[x])

    def stretches(self, text: np.ndarray, place: np.ndarray, word: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(text, member, first word, end word) of the parts of texts with enough hits of a member.

        The texts stand one after the other in blocks, with so many empty blocks between them that what is counted together is of one text.
        """
        times = self.times[word]
        some = times > 0
        text, place, word, times = text[some], place[some], word[some], times[some]
        n, found = len(self.members), [np.zeros((3, 0), "i8")]
        real = -(-size // self.block)
        ends = np.cumsum(real + BLOCKS - 1) - BLOCKS + 1
        base, blocks = ends - real, int(ends[-1]) + BLOCKS - 1
        block = base[text] + place // self.block
        step = max(BLOCKS, COUNTERS // n - BLOCKS)
        for begin in range(0, blocks, step):
            held = min(step + BLOCKS - 1, blocks - begin)
            i, j = np.searchsorted(block, [begin, begin + held])
            if i == j or held < BLOCKS:
                continue
            m = times[i:j]
            owner = self.owner[np.arange(m.sum()) + np.repeat(self.start[word[i:j]] - np.cumsum(m) + m, m)]
            total = np.zeros((held + 1, n), "i4")
            np.cumsum(np.bincount(np.repeat(block[i:j] - begin, m) * n + owner, minlength=held * n).reshape(held, n), 0, out=total[1:])
            b, k = np.nonzero(total[BLOCKS:] - total[:-BLOCKS] >= self.need)
            t = np.searchsorted(ends, b + begin, "right")
            # counts over an edge of a text are no more than those within it
            b = np.clip(b + begin, base[t], np.maximum(base[t], ends[t] - BLOCKS)) - base[t]
            found.append(self._spread(np.stack([t * n + k, b, b])))
        key, low, high = self._spread(np.concatenate(found, 1))
        t = key // n
        return t, key % n, low * self.block, np.minimum(size[t], (high + BLOCKS) * self.block)

    @staticmethod
    def _spread(rows: np.ndarray) -> np.ndarray:
        """Each key once, with its least low and greatest high."""
        if not rows.shape[1]:
            return rows
        rows = rows[:, np.argsort(rows[0], kind="stable")]
        at = np.flatnonzero(np.diff(rows[0], prepend=-1))
        return np.stack([rows[0][at], np.minimum.reduceat(rows[1], at), np.maximum.reduceat(rows[2], at)])


class Index:
    """A slice of the benchmark: items as word numbers, and the documents of the corpus that hold each word (which only speed depends on)."""

    def __init__(self, items: list[tuple[int, list[str]]]):
        self.items = [(i, w) for i, w in items if w]
        self.number: dict[str, int] = {}
        self.coded = [np.array([self.number.setdefault(x, len(self.number)) for x in w], "i8") for _, w in self.items]
        self.frequency = np.zeros(len(self.number), "i8")
        self.plans: dict[float, list[Plan]] = {}

    def codes(self, words: list[str]) -> np.ndarray:
        return np.fromiter(map(self.number.get, words, repeat(-1)), "i8", len(words))

    def plan(self, similarity: float) -> list[Plan]:
        """Items by length class. An alignment of m matches scores at most 2 m less one for each other word it spans, and m is at most the item's length."""
        if similarity not in self.plans:
            classes: dict[int, list[tuple[int, int, int]]] = {}
            for k, item in enumerate(self.coded):
                goal = max(1, int(np.ceil(similarity * MATCH * len(item) - 1e-9)))
                if goal <= MATCH * len(item):
                    classes.setdefault(len(item).bit_length(), []).append((k, goal, (MATCH + 1) * len(item) - goal))
            self.plans[similarity] = [Plan(self, [k for k, _, _ in c], [g for _, g, _ in c], max(s for _, _, s in c)) for _, c in sorted(classes.items())]
        return self.plans[similarity]

    def leaks(self, words: list[str], similarity: float) -> list[tuple[int, float, int, int]]:
        """(item, similarity, first word, end word) of every item that a stretch of the text aligns with well enough."""
        return self.leaks_of([words], similarity)[0]

    def leaks_of(self, texts: Iterable[list[str]], similarity: float) -> list[list[tuple[int, float, int, int]]]:
        """``leaks`` of each text; hits are counted in all of them together."""
        coded = [self.codes(words) for words in texts]
        out, known = [[] for _ in coded], None
        size, flat = np.array([len(x) for x in coded], "i8"), np.concatenate([*coded, np.zeros(0, "i8")])
        at = np.flatnonzero(flat >= 0)
        text = np.repeat(np.arange(len(coded)), size)[at]
        place, word = at - (np.cumsum(size) - size)[text], flat[at]
        for plan in self.plan(similarity) if len(at) else ():
            for t, member, first, end in plan.candidates(text, place, word, size):
                codes = coded[t]
                k, goal = plan.members[member], plan.goals[member]
                item, best = self.coded[k], (0, 0, 0)
                known = np.zeros(len(self.number) + 1, bool) if known is None else known
                known[item] = True
                window = codes[first:end]
                # words that the item lacks cost one each: a word is in no good alignment if every sum of a stretch around it is too low
                total = np.concatenate([[0], np.cumsum(np.where(known[window], MATCH, MISMATCH))])
                known[item] = False
                reach = np.maximum.accumulate(total[:0:-1])[::-1] - np.minimum.accumulate(total[:-1])
                edges = np.flatnonzero(np.diff(np.concatenate([[False], reach >= goal, [False]]).astype("i1")))
                for i, j in zip(edges[::2], edges[1::2]):
                    if best[0] == MATCH * len(item):
                        break
                    # no alignment can score more than what the stretch has of the item's words
                    if MATCH * np.isin(item, window[i:j]).sum() >= goal and (score := smith_waterman(item, window[i:j])) > best[0]:
                        best = (score, first + int(i), first + int(j))
                if best[0] >= goal:
                    out[t].append((self.items[k][0], best[0] / (MATCH * len(item)), *best[1:]))
        return [sorted(x) for x in out]


def _slices(benchmark: DataFrame, item_id: str, text: str) -> Iterator[list[tuple[int, list[str]]]]:
    """The benchmark's items in slices of at most ``SLICE_BYTES``, so that what each task gets is bounded."""
    rows, size = [], 0
    held = benchmark.where(F.col(item_id).isNotNull() & F.col(text).isNotNull()).select(F.col(item_id).cast("long").alias("i"), F.col(text).alias("t"))
    for r in held.toLocalIterator():
        n = len(r["t"].encode("utf-8", "surrogatepass"))
        if rows and size + n > SLICE_BYTES:
            yield rows
            rows, size = [], 0
        rows.append((r["i"], words_of(r["t"])))
        size += n
    if rows:
        yield rows


def _count(index: Index) -> Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]]:
    """Documents of this task in which each word of the benchmark stands, summed before they leave it."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        total = np.zeros(len(index.number), "i8")
        for batch in batches:
            for t in batch["text"]:
                total[[index.number[w] for w in index.number.keys() & set(words_of(t))]] += 1
        at = np.flatnonzero(total)
        yield pd.DataFrame({"word": at, "n": total[at]})

    return run


def build_indexes(docs: DataFrame, benchmark: DataFrame, text: str = "text", item_id: str = "item_id", item_text: str = "text") -> Iterator[Index]:
    """Indexes of the benchmark, slice by slice, rarity of words taken from the frequencies in all of ``docs``."""
    bound_batches(docs.sparkSession)
    for items in _slices(benchmark, item_id, item_text):
        index = Index(items)
        counts = docs.select(F.col(text).alias("text")).mapInPandas(_count(index), "word long, n long").groupBy("word").agg(F.sum("n").alias("n"))
        # as many rows as the slice has words, which SLICE_BYTES bounds
        for r in counts.collect():
            index.frequency[r["word"]] = r["n"]
        yield index


def with_leaks(docs: DataFrame, index: Index, text: str = "text", out: str = "leaks", similarity: float = SIMILARITY) -> DataFrame:
    """Add ``out``: array of struct item_id, similarity, first_word, end_word of the items that the whole text contains a copy of.

    Similarity is the best local alignment's score as a share of the item's own; every item that reaches ``similarity`` is found. Null, empty and wordless texts have an empty array;
    items without a word match nothing; items of equal text are all named. Texts are whole: what is held of a very long one is a number for each word.
    Rows and other columns stay, but a column named as ``out`` is replaced.
    """
    bound_batches(docs.sparkSession)

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in batches:
            yield pd.Series([[dict(zip(("item_id", "similarity", "first_word", "end_word"), x)) for x in found] for found in index.leaks_of(map(words_of, batch), similarity)])

    return docs.withColumn(out, F.pandas_udf(run, "array<struct<item_id:long,similarity:double,first_word:int,end_word:int>>")(F.col(text)))


def leaked_items(docs: DataFrame, benchmark: DataFrame, doc_id: str = "doc_id", text: str = "text", similarity: float = SIMILARITY) -> DataFrame:
    """doc_id, item_id, similarity of every document and item that align well enough; one row for each pair and row of ``docs``."""
    kind, found = docs.schema[doc_id].dataType, None
    # as text, for a batch with a null would turn whole numbers into doubles
    rows = docs.select(F.col(doc_id).cast("string").alias("doc_id"), F.col(text).alias("text"))
    for index in build_indexes(docs, benchmark, text):
        part = rows.mapInPandas(_pairs(index, similarity), "doc_id string, item_id long, similarity double").withColumn("doc_id", F.col("doc_id").cast(kind))
        found = part if found is None else found.unionByName(part)
    if found is None:
        return rows.select(F.col("doc_id").cast(kind).alias("doc_id"), F.lit(None).cast("long").alias("item_id"), F.lit(None).cast("double").alias("similarity")).where("false")
    return found


def _pairs(index: Index, similarity: float) -> Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]]:
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            leaks = index.leaks_of(map(words_of, batch["text"]), similarity)
            at = np.repeat(np.arange(len(leaks)), [len(x) for x in leaks])
            flat = [x for some in leaks for x in some]
            yield pd.DataFrame({"doc_id": batch["doc_id"].iloc[at].reset_index(drop=True), "item_id": [x[0] for x in flat], "similarity": [x[1] for x in flat]})

    return run


def decontaminate(docs: DataFrame, benchmark: DataFrame, text: str = "text", similarity: float = SIMILARITY) -> DataFrame:
    """Rows of ``docs`` that contain no copy of a benchmark item; columns stay."""
    out = docs
    for index in build_indexes(docs, benchmark, text):
        (mark,) = fresh(out, "leaks")
        out = with_leaks(out, index, text, mark, similarity).where(F.size(mark) == 0).drop(mark)
    return out
