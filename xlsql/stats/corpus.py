"""Corpus statistics of questions, evidence and SQL by language and split."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from xlsql.functions.text import tokens, words

#: Tasks over which the occurrences of one frequent token are dealt before they are added up.
SALTS = 16


def tokenize(text: Column, tokenizer: str = "word_punct", n: int = 3) -> Column:
    """Array of tokens: word_punct, whitespace, or char_ngram (every n characters)."""
    if tokenizer == "word_punct":
        return tokens(text)
    if tokenizer == "whitespace":
        return words(text)
    if tokenizer == "char_ngram":
        return F.when(F.length(text) >= n, F.transform(F.sequence(F.lit(1), F.length(text) - n + 1), lambda i: F.substring(text, i, F.lit(n)))).otherwise(F.array())
    raise ValueError(tokenizer)


def token_count(text: Column, tokenizer: str = "word_punct", n: int = 3) -> Column:
    if tokenizer == "char_ngram":
        return F.greatest(F.length(text) - (n - 1), F.lit(0))
    return F.size(tokenize(text, tokenizer, n))


def length_stats(df: DataFrame, text: str, by: Sequence[str]) -> DataFrame:
    """by, n, avg_words, avg_chars, avg_tokens, tokens: one pass, one small aggregate."""
    t = F.col(text)
    size = F.size(tokens(t))
    return df.groupBy(*by).agg(
        F.count("*").alias("n"), F.round(F.avg(F.size(words(t))), 6).alias("avg_words"), F.round(F.avg(F.length(t)), 6).alias("avg_chars"),
        F.round(F.avg(size), 6).alias("avg_tokens"), F.sum(size).cast("long").alias("tokens"),
    )


def token_frequencies(df: DataFrame, text: str, by: Sequence[str], tokenizer: str = "word_punct", casefold: bool = True) -> DataFrame:
    """by, token, n. Partial sums meet first, so the most frequent token costs one row for each task."""
    t = F.lower(F.col(text)) if casefold else F.col(text)
    return df.select(*by, F.explode(tokenize(t, tokenizer)).alias("token")).groupBy(*by, "token").agg(F.count("*").alias("n"))


def vocabulary(df: DataFrame, text: str, by: Sequence[str], exact: bool = True, casefold: bool = True) -> DataFrame:
    """by, vocab: distinct tokens, exact in two levels, or by sketch."""
    if exact:
        return token_frequencies(df, text, by, casefold=casefold).groupBy(*by).agg(F.count("*").alias("vocab"))
    t = F.lower(F.col(text)) if casefold else F.col(text)
    return df.select(*by, F.explode(tokens(t)).alias("token")).groupBy(*by).agg(F.approx_count_distinct("token", 0.01).alias("vocab"))


def corpus_stats(df: DataFrame, text: str, by: Sequence[str]) -> DataFrame:
    """All length statistics, vocabulary and type-token ratio (distinct tokens over all tokens)."""
    both = length_stats(df, text, by).join(vocabulary(df, text, by), list(by))
    return both.withColumn("ttr", F.round(F.col("vocab") / F.col("tokens"), 6))


MEASURES = ("avg_words", "avg_chars", "avg_tokens", "vocab", "ttr")


def percent_change(stats: DataFrame, group: str, base: str, measures: Sequence[str] = MEASURES) -> DataFrame:
    """group, measure, base_value, value, change: percent change of each measure against the row whose ``group`` is ``base``."""
    long = stats.select(group, F.explode(F.array(*[F.struct(F.lit(m).alias("measure"), F.col(m).cast("double").alias("value")) for m in measures])).alias("x")).select(group, "x.*")
    # one row for each measure
    own = F.broadcast(long.where(F.col(group) == base).select("measure", F.col("value").alias("base_value")))
    return long.where(F.col(group) != base).join(own, "measure").select(group, "measure", "base_value", "value", F.round(100 * (F.col("value") / F.col("base_value") - 1), 4).alias("change"))


def fertility(df: DataFrame, text: str, by: Sequence[str], tokenizer: str = "word_punct", n: int = 3) -> DataFrame:
    """by, tokenizer, fertility (tokens per word), compression (characters per token)."""
    t = F.col(text)
    sums = df.groupBy(*by).agg(F.sum(token_count(t, tokenizer, n)).alias("t"), F.sum(F.size(words(t))).alias("w"), F.sum(F.length(t)).alias("c"))
    return sums.select(*by, F.lit(tokenizer).alias("tokenizer"), F.round(F.col("t") / F.col("w"), 6).alias("fertility"), F.round(F.col("c") / F.col("t"), 6).alias("compression"))


def sparsity(df: DataFrame, text: str, by: Sequence[str], rare: int = 2) -> DataFrame:
    """by, types, hapax_share (types seen once), tail_share (occurrences of types seen at most ``rare`` times)."""
    f = token_frequencies(df, text, by)
    s = f.groupBy(*by).agg(F.count("*").alias("types"), F.avg((F.col("n") == 1).cast("double")).alias("h"), F.sum(F.when(F.col("n") <= rare, F.col("n")).otherwise(0)).alias("t"), F.sum("n").alias("all"))
    return s.select(*by, "types", F.round("h", 6).alias("hapax_share"), F.round(F.col("t") / F.col("all"), 6).alias("tail_share"))


def train_bpe(df: DataFrame, text: str, merges: int = 20) -> list[tuple[str, str]]:
    """Merges of a sub-word tokenizer, most frequent pair first, ties in order.

    Works on distinct words with their counts, kept as arrays of symbols; each merge is one aggregation with partial sums and one
    row for the driver.
    """
    vocab = token_frequencies(df, text, [], "whitespace").select(F.filter(F.split("token", ""), lambda c: c != "").alias("s"), "n").cache()
    done: list[tuple[str, str]] = []
    for _ in range(merges):
        pairs = apply_bpe_to(vocab, done).select(F.explode(F.zip_with(F.slice("s", 1, F.greatest(F.size("s") - 1, F.lit(0))), F.slice("s", 2, F.greatest(F.size("s") - 1, F.lit(0))), lambda a, b: F.struct(a.alias("a"), b.alias("b")))).alias("p"), "n")
        top = pairs.groupBy("p.a", "p.b").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "a", "b").first()
        if top is None or top["n"] < 2:
            break
        done.append((top["a"], top["b"]))
    vocab.unpersist()
    return done


def _merge(symbols: Column, a: str, b: str) -> Column:
    """Join neighbours a, b from left to right; an array of symbols whose separator is a control sign."""
    joined = F.concat(F.lit("\x01"), F.array_join(symbols, "\x01\x01"), F.lit("\x01"))
    return F.split(F.trim(F.replace(joined, F.lit(f"\x01{a}\x01\x01{b}\x01"), F.lit(f"\x01{a}{b}\x01")), F.lit("\x01")), "\x01\x01")


def apply_bpe_to(vocab: DataFrame, merges: Sequence[tuple[str, str]], symbols: str = "s") -> DataFrame:
    out = vocab
    for a, b in merges:
        out = out.withColumn(symbols, _merge(F.col(symbols), a, b))
    return out


def bpe_fertility(df: DataFrame, text: str, by: Sequence[str], merges: Sequence[tuple[str, str]]) -> DataFrame:
    """Tokens per word of each group under the learnt merges."""
    f = token_frequencies(df, text, by, "whitespace").select(*by, F.filter(F.split("token", ""), lambda c: c != "").alias("s"), "n")
    return apply_bpe_to(f, merges).groupBy(*by).agg(F.round(F.sum(F.size("s") * F.col("n")) / F.sum("n"), 6).alias("fertility"))


def order_inversions(links: DataFrame, key: str = "item_id") -> DataFrame:
    """key, links, inversions: pairs of links (pos_text, pos_sql) whose order differs between text and SQL.

    A reversed pair is found within each item's own short array of links.
    """
    pairs = F.array_sort(F.collect_list(F.struct("pos_text", "pos_sql")))
    held = links.groupBy(key).agg(pairs.alias("p"))
    crossed = F.aggregate(F.sequence(F.lit(0), F.size("p") - 1), F.lit(0), lambda s, i: s + F.size(F.filter(F.slice(F.col("p"), i + 2, F.size("p")), lambda y: (y["pos_text"] > F.get(F.col("p"), i)["pos_text"]) & (y["pos_sql"] < F.get(F.col("p"), i)["pos_sql"]))))
    return held.select(key, F.size("p").alias("links"), crossed.alias("inversions"))
