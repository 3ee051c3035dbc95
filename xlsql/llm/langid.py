"""Language identification: interpolated Kneser-Ney models of characters, in sorted hash arrays."""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xlsql.llm.columns import fresh
from xlsql.session import bound_batches

ORDER = 4
DISCOUNT = 0.75
#: Bounds of the labelled sample that the models are fitted on: documents of each language, and bytes of their whole texts.
SAMPLE_DOCS, SAMPLE_BYTES = 400, 2 << 20
MOST_LANGUAGES = 256
#: Of each language every so many texts calibrate its rejection instead of its model, if there are at least this many texts for either; else the slack in bits.
HELD_OUT, LEAST_TEXTS, SLACK = 5, 20, 2.0
#: Standard errors of a text's entropy that are allowed for, and how far beyond the worst calibrating text the slack goes, at least a bit.
SIGMAS, BEYOND = 6.0, 2.0
#: Words whose scores a worker remembers, and how many are scored together.
REMEMBERED, WORDS_AT_ONCE = 150_000, 16_384
#: Characters after which more text no longer raises the confidence.
FULL_CHARS = 60
UNKNOWN = "und"
WORD = re.compile(r"[^\W\d_]+").findall
MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)


def _codes(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of all words, each between spaces, and the number of the word of each."""
    flat = np.frombuffer((" " + " ".join(words) + " ").encode("utf-32-le"), "<u4").astype("u8")
    word = np.cumsum(flat == 32) - 1
    return flat, word


def _grams(flat: np.ndarray, order: int) -> np.ndarray:
    """Hash of the ``order`` characters that end at each place from order - 1 on."""
    h = np.zeros(len(flat) - order + 1, "u8")
    for k in range(order):
        h = (h ^ flat[k : len(flat) - order + 1 + k]) * MULTIPLIER
        h ^= h >> np.uint64(29)
    return h


@dataclass
class Models:
    """Per order the sorted hashes of all n-grams, and for each the log-probability of its last character in every language.

    ``back`` has the log-weight of backing off from a context that a language knows; a missing one is 0.
    """

    languages: list[str]
    keys: list[np.ndarray]
    logp: list[np.ndarray]
    context: list[np.ndarray]
    back: list[np.ndarray]
    floor: np.ndarray
    mean: np.ndarray
    spread: np.ndarray
    slack: np.ndarray

    def limit(self, language: int, characters: float, sigmas: float) -> float:
        """Entropy above which a text of so many characters is none of the language."""
        return self.mean[language] + self.slack[language] + sigmas * self.spread[language] / np.sqrt(characters)

    def word_scores(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Sum of the log-probabilities (bits) of each word's characters and its end in every language, and their number."""
        flat, word = _codes(words)
        n, order = len(flat), len(self.keys)
        ends = np.arange(1, n)
        # an n-gram reaches back to the space before its word at most
        space = np.maximum.accumulate(np.where(flat == 32, np.arange(n), 0))
        usable = np.zeros(n, int)
        usable[1:] = np.minimum(ends - space[:-1] + 1, order)
        total, penalty, todo = np.zeros((n, len(self.languages))), np.zeros((n, len(self.languages))), ends
        for k in range(order, 0, -1):
            at = todo[usable[todo] >= k]
            if not len(at):
                continue
            h = _grams(flat, k)[at - k + 1]
            found, i = _lookup(self.keys[k - 1], h)
            hit = at[found]
            total[hit] = self.logp[k - 1][i[found]] + penalty[hit]
            miss = at[~found]
            if k > 1 and len(miss):
                f, j = _lookup(self.context[k - 1], _grams(flat, k - 1)[miss - k + 1])
                penalty[miss[f]] += self.back[k - 1][j[f]]
            elif len(miss):
                total[miss] = self.floor + penalty[miss]
            done = np.zeros(n, bool)
            done[hit] = True
            todo = todo[~done[todo]]
        owner = np.where(flat == 32, word - 1, word)[1:]
        sums = np.stack([np.bincount(owner, total[1:, c], len(words)) for c in range(len(self.languages))], 1)
        return sums, np.bincount(owner, minlength=len(words))


    def entropy(self, text: str, language: int) -> tuple[float, float]:
        """Bits a character of a whole text in one language, and the number of its characters."""
        words = Counter(letters(text))
        held, times = list(words), np.array(list(words.values()), float)
        bits = size = 0.0
        for k in range(0, len(held), WORDS_AT_ONCE):
            s, n = self.word_scores(held[k : k + WORDS_AT_ONCE])
            bits, size = bits - (s[:, language] * times[k : k + WORDS_AT_ONCE]).sum(), size + (n * times[k : k + WORDS_AT_ONCE]).sum()
        return bits / size if size else 0.0, size


def _lookup(keys: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    if not len(keys):
        return np.zeros(len(h), bool), np.zeros(len(h), int)
    i = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
    return keys[i] == h, i


def letters(text: str | None) -> list[str]:
    """Lower-cased runs of letters of a whole text; none if it has signs that only count as letters, such as fractions."""
    words = WORD(text.lower()) if text else []
    return words if any(c.isalpha() for w in words for c in w) else []


def train(samples: dict[str, list[str]], order: int = ORDER) -> Models:
    """Fit one interpolated Kneser-Ney model to the texts of each language.

    Counts of the highest order are occurrences; those of lower orders are the numbers of distinct characters that precede. All
    n-grams that any language has seen are stored with every language's interpolated value, so a lookup never mixes orders between languages.
    Every fifth text is kept out of a language's model where there are enough, to calibrate how far a text of the language may lie from it.
    """
    languages = sorted(samples)
    if not languages:
        return Models([], [], [], [], [], np.zeros(0), np.zeros(0), np.zeros(0), np.zeros(0))
    counted, spoken, apart = [], [], []
    for lang in languages:
        enough = len(samples[lang]) >= LEAST_TEXTS
        apart.append([t for k, t in enumerate(samples[lang]) if enough and k % HELD_OUT == 0])
        words = Counter(w for k, t in enumerate(samples[lang]) if not enough or k % HELD_OUT for w in letters(t))
        spoken.append(words)
        grams: list[Counter] = [Counter() for _ in range(order)]
        for w, c in words.items():
            s = f" {w} "
            for i in range(1, len(s)):
                for k in range(min(order, i + 1)):
                    grams[k][s[i - k : i + 1]] += c
        counted.append(grams)
    n_lang = len(languages)
    seen = [sorted({g for grams in counted for g in grams[k]}) for k in range(order)]
    alphabet = len(seen[0]) + 1
    prob = np.zeros((0, n_lang))
    place: dict[str, int] = {}
    keys, logp, context, back = [], [], [], []
    for k in range(order):
        top = k == order - 1
        value = np.zeros((len(seen[k]), n_lang))
        here = {g: i for i, g in enumerate(seen[k])}
        ctx = sorted({g[:-1] for g in seen[k]} | ({""} if not k else set()))
        at_ctx = {g: i for i, g in enumerate(ctx)}
        weight = np.ones((len(ctx), n_lang))
        for c, grams in enumerate(counted):
            # nothing precedes the space at which a word begins: n-grams from there keep their occurrences
            kn = grams[k] if top else Counter({g: v for g, v in grams[k].items() if k and g[0] == " "})
            if not top:
                kn.update(g[1:] for g in grams[k + 1])
            totals, kinds = Counter(), Counter()
            for g, v in kn.items():
                totals[g[:-1]] += v
                kinds[g[:-1]] += 1
            for g, i in at_ctx.items():
                if totals[g]:
                    weight[i, c] = DISCOUNT * kinds[g] / totals[g]
            for g, i in here.items():
                lower = prob[place[g[1:]], c] if k else 1 / alphabet
                t = totals[g[:-1]]
                value[i, c] = (max(kn[g] - DISCOUNT, 0) / t if t else 0) + weight[at_ctx[g[:-1]], c] * lower
        flat = [np.frombuffer(g.encode("utf-32-le"), "<u4").astype("u8") for g in seen[k]]
        h = np.array([_grams(f, k + 1)[0] for f in flat], "u8")
        o = np.argsort(h)
        keys.append(h[o])
        logp.append(np.log2(value[o]))
        hc = np.array([_grams(np.frombuffer(g.encode("utf-32-le"), "<u4").astype("u8"), k)[0] for g in ctx] if k else [0], "u8")
        oc = np.argsort(hc)
        context.append(hc[oc])
        back.append(np.log2(weight[oc]))
        prob, place = value, here
    floor = back[0][0] - np.log2(alphabet)
    models = Models(languages, keys, logp, context, back, floor, np.zeros(n_lang), np.ones(n_lang), np.full(n_lang, SLACK))
    for c, words in enumerate(spoken):
        held, times = list(words), np.array(list(words.values()), float)
        scored = [models.word_scores(held[k : k + WORDS_AT_ONCE]) for k in range(0, len(held), WORDS_AT_ONCE)]
        if not scored:
            continue
        bits, n = -np.concatenate([x[:, c] for x, _ in scored]), np.concatenate([x for _, x in scored])
        total, size = (bits * times).sum(), (n * times).sum()
        models.mean[c] = total / size
        square = ((bits - models.mean[c] * n) ** 2 / n * times).sum()
        models.spread[c] = np.sqrt(square / times.sum())
        worst = [e - models.mean[c] - SIGMAS * models.spread[c] / np.sqrt(size) for e, size in (models.entropy(t, c) for t in apart[c]) if size]
        if worst:
            models.slack[c] = max(1.0, BEYOND * max(worst))
    return models


def fit(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", lang: str = "lang", per_language: int = SAMPLE_DOCS, most_bytes: int = SAMPLE_BYTES) -> Models:
    """Models of the languages of ``docs``, fitted on the whole texts of at most ``per_language`` documents of each and at most ``most_bytes`` of them, the first by a hash of their ids.

    Rows with a null text or lang teach nothing; of rows that share an id and a language the least text counts. At most ``MOST_LANGUAGES`` languages are
    taken, else this raises.
    """
    known = docs.where(F.col(text).isNotNull() & F.col(lang).isNotNull()).select(F.col(lang).cast("string").alias("lang"), F.pmod(F.xxhash64(F.col(doc_id)), F.lit(1 << 30)).alias("place"), F.col(text).alias("text"))
    sizes = known.groupBy("lang").count().limit(MOST_LANGUAGES + 1).collect()
    if len(sizes) > MOST_LANGUAGES:
        raise ValueError(f"more than {MOST_LANGUAGES} languages")
    if not sizes:
        return train({})
    # about twice the wanted share by hash, cut to the wanted number here; places are counted before any text is read whole
    share = F.create_map(*[F.lit(x) for r in sizes for x in (r["lang"], min(1.0, 2 * per_language / r["count"]))])
    near = known.where(F.col("place") < F.element_at(share, F.col("lang")) * (1 << 30))
    held: dict[str, list[int]] = {}
    total: Counter[str] = Counter()
    for r in sorted(near.groupBy("lang", "place").agg(F.min(F.octet_length("text")).alias("bytes")).collect()):
        if len(held.setdefault(r["lang"], [])) < per_language and total[r["lang"]] + r["bytes"] <= most_bytes:
            held[r["lang"]].append(r["place"])
            total[r["lang"]] += r["bytes"]
    chosen = docs.sparkSession.createDataFrame([(k, p) for k, v in held.items() for p in v], "lang string, place long")
    rows = near.join(F.broadcast(chosen), ["lang", "place"]).groupBy("lang", "place").agg(F.min_by("text", F.struct(F.octet_length("text"), "text")).alias("text"))
    samples: dict[str, list] = {}
    for r in sorted(rows.collect(), key=lambda r: (r["lang"], r["place"])):
        samples.setdefault(r["lang"], []).append(r["text"])
    return train(samples)


def with_language(docs: DataFrame, models: Models, text: str = "text", out: str = "language", sigmas: float = SIGMAS) -> DataFrame:
    """Add a struct column ``out``: lang, score, entropy, rejected.

    lang: the language of the lowest cross-entropy (bits a character over the letters of the whole text), ties to the first in
    order; ``und`` for null texts and texts without a letter, with score 0. score: weight of that language against the others, from
    entropies over at most ``FULL_CHARS`` characters. rejected: ``und``, or an entropy above the mean of the language's own training
    words by more than ``sigmas`` standard errors of a text of that length and the slack that texts kept out of the fit have shown to be needed. Texts are whole, of any length; rows and other columns stay,
    but a column named as ``out`` is replaced.
    """
    bound_batches(docs.sparkSession)

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        memory: dict[str, int] = {}
        sums = np.zeros((0, len(models.languages)))
        sizes = np.zeros(0)
        for batch in batches:
            texts = [letters(t) for t in batch]
            new = list({w for t in texts for w in t if w not in memory})
            if len(memory) + len(new) > REMEMBERED:
                memory.clear()
                sums, sizes, new = sums[:0], sizes[:0], list({w for t in texts for w in t})
            for k in range(0, len(new) if models.languages else 0, WORDS_AT_ONCE):
                part = new[k : k + WORDS_AT_ONCE]
                s, n = models.word_scores(part)
                memory.update(zip(part, range(len(sums), len(sums) + len(part))))
                sums, sizes = np.concatenate([sums, s]), np.concatenate([sizes, n])
            rows = []
            for words in texts:
                if not words or not models.languages:
                    rows.append((UNKNOWN, 0.0, None, True))
                    continue
                at = np.fromiter(map(memory.__getitem__, words), "i8", len(words))
                n = sizes[at].sum()
                entropy = -sums[at].sum(0) / n
                best = int(entropy.argmin())
                score = 1 / np.exp2((entropy[best] - entropy) * min(n, FULL_CHARS)).sum()
                rows.append((models.languages[best], float(score), float(entropy[best]), bool(entropy[best] > models.limit(best, n, sigmas))))
            yield pd.DataFrame(rows, columns=["lang", "score", "entropy", "rejected"])

    return docs.withColumn(out, F.pandas_udf(run, "lang string, score double, entropy double, rejected boolean")(F.col(text)))


def keep_identified(docs: DataFrame, models: Models, text: str = "text", **limits) -> DataFrame:
    """Rows of ``docs`` whose language is told apart; null and letterless texts and strange ones go. Columns stay."""
    (mark,) = fresh(docs, "language")
    return with_language(docs, models, text, mark, **limits).where(~F.col(f"{mark}.rejected")).drop(mark)
