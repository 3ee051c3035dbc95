"""Secret scans with DataFrame functions only: fixed patterns, and Markov models of random strings and identifiers."""

from __future__ import annotations

import hashlib
import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from xlsql.llm.columns import fresh

# The base patterns.
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
KINDS = ("assign", "access", "hex", "markov")
#: What the models judge: every stretch of this alphabet of at least ``LEAST`` characters, or what base spans leave of it.
CANDIDATE = r"[A-Za-z0-9+/_=-]{20,}"
LEAST = 20
MIXED = r"[A-Za-z+/_=-][0-9]|[0-9][A-Za-z+/_=-]|[a-z][A-Z][A-Za-z+/_=-]*[a-z][A-Z]"
SPANS = "array<struct<start:int,kind:int,end:int,value:string>>"
#: Matches that are put together at once.
BLOCK = 256
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-"
#: Mean log-likelihood ratio for each transition above which a stretch counts as random (nats).
RATIO = 0.25

#: Words that ordinary identifiers are made of; the labelled ordinary samples join them in the usual ways.
COMMON = (
    "account action address agent album amount application array article async average balance base batch begin binary block board body border bound "
    "branch browser bucket buffer build button cache calendar call category chain channel character chart check child class clean client close cloud cluster "
    "code collection color column command comment commit common compare component config connection console constant container content context control "
    "convert cookie copy count country create current cursor customer data database date debug decode default delete delta device dialog digest dimension "
    "directory disable discount display distance document domain download draft driver dynamic editor element email employee enable encode encoding end engine "
    "entry error event example exchange execute export expression factory feature fetch field file filter final first flag float folder font footer format "
    "forward frame from function future gateway general generate global graph group handler hash header health height helper hidden history home host icon "
    "identifier image import index info initial input insert install instance integer interface internal invoice item iterator join key label language last layer "
    "layout length level library license limit line link list load local location lock login logger loop machine main manager map market mask master match "
    "maximum member memory menu merge message metadata method middle minimum mobile mode model module monitor mouse move name native network next node "
    "notification null number object offset open operation option order origin output owner package page panel parameter parent parser partition password path "
    "pattern payment permission person phone picture pixel platform player plugin point policy pool position preview previous price primary print priority "
    "private process product profile progress project property protocol provider public query queue quick random range rate ready record region register "
    "release remote render repeat replace report request reset resource response result return right role root route router row rule sample schedule schema "
    "scope screen script search second section select sender sequence serial server service session setting shape share shipping signal simple single size slot "
    "small socket sort source space split stack stage start state static status stock stop storage store stream string style submit summary support switch "
    "symbol system table target task temp template terminal test text theme thread ticket time title toggle token tool total trace track trade transaction "
    "transfer tree trigger type unique unit update upload user utility valid value variable vector vendor version video view visible volume wallet warning "
    "watch weight widget width window worker world wrapper write year zone"
).split()


def labelled_samples(n: int = 3000) -> list[tuple[str, int]]:
    """Labelled strings: 1 random (hexadecimal, base 64, base 36 of digests), 0 ordinary identifiers, paths and numbered names."""
    out = []
    for i in range(n):
        d = hashlib.sha512(f"sample {i}".encode()).digest()
        big = int.from_bytes(d, "big")
        pick = lambda letters: "".join(letters[(big >> 7 * k) % len(letters)] for k in range(20 + i % 24))  # noqa: E731,B023
        out.append((d.hex()[: 24 + i % 40] if i % 3 == 0 else pick(ALPHABET[:62]) if i % 3 == 1 else pick(ALPHABET[:36] if i % 2 else ALPHABET), 1))
        words = [COMMON[d[k] * 256 + d[k + 1] and (d[k] * 256 + d[k + 1]) % len(COMMON)] for k in range(0, 10, 2)]
        words = words[: 2 + d[20] % 4]
        number = ("", str(d[21]), str(2000 + d[22] % 30), "v" + str(d[23] % 10))[d[24] % 4]
        style = d[25] % 6
        plain = {0: "_".join(words), 1: "-".join(words), 2: words[0] + "".join(w.title() for w in words[1:]), 3: "".join(w.title() for w in words), 4: "/".join(words), 5: "_".join(words).upper()}[style]
        out.append((plain + (("_" if style in (0, 5) else "-" if style == 1 else "") + number if number else ""), 0))
    return out


def train(samples: list[tuple[str, int]], smoothing: float = 0.5) -> list[float]:
    """Log-likelihood ratios (random against ordinary) of character transitions of two first-order Markov models.

    Row-major over the alphabet and one class for every other character; the row of that class also starts each string.
    """
    size, place = len(ALPHABET) + 1, {c: i for i, c in enumerate(ALPHABET)}
    counts = [[smoothing] * (size * size) for _ in range(2)]
    for text, label in samples:
        before = size - 1
        for c in text:
            now = place.get(c, size - 1)
            counts[label][before * size + now] += 1
            before = now
    rows = [[sum(c[r * size : (r + 1) * size]) for r in range(size)] for c in counts]
    return [math.log(counts[1][i] / rows[1][i // size]) - math.log(counts[0][i] / rows[0][i // size]) for i in range(size * size)]


def markov_ratio(token: Column, table: list[float]) -> Column:
    """Mean log-likelihood ratio for each transition of ``token``."""
    size = len(ALPHABET) + 1
    place = [size - 1] * 128
    for i, c in enumerate(ALPHABET):
        place[ord(c)] = i
    code, ratio = F.array(*[F.lit(x) for x in place]), F.array(*[F.lit(round(x, 6)) for x in table])
    known = lambda c: F.when(F.ascii(c) < 128, F.get(code, F.ascii(c))).otherwise(F.lit(size - 1))
    letters = F.filter(F.split(token, ""), lambda c: c != "")
    start = F.struct(F.lit(0.0).alias("sum"), F.lit(size - 1).alias("at"))
    step = lambda s, c: F.struct((s["sum"] + F.get(ratio, s["at"] * size + known(c))).alias("sum"), known(c).alias("at"))
    return F.aggregate(letters, start, step, lambda s: s["sum"] / F.greatest(F.lit(1), F.length(token)))


def _located(text: Column, pattern: str, kind: int, keep) -> Column:
    """Array of struct start, kind, end, value: matches of ``pattern`` at code-point offsets; ``keep`` filters afterwards.

    The pieces between matches give the offsets: each match begins where the pieces and matches before it end.
    """
    found = F.regexp_extract_all(text, F.lit(f"(?s)({pattern})"), F.lit(1))
    gaps = F.split(text, pattern, -1)
    zero = F.struct(F.lit(0).alias("at"), F.array().cast(SPANS).alias("out"))

    def step(s: Column, x: Column) -> Column:
        begin = s["at"] + x["gap"]
        end = begin + F.length(x["value"])
        span = F.struct(begin.alias("start"), F.lit(kind).alias("kind"), end.alias("end"), x["value"].alias("value"))
        return F.struct(end.alias("at"), F.concat(s["out"], F.array(span)).alias("out"))

    def join(s: Column, x: Column) -> Column:
        moved = F.transform(x["out"], lambda y: F.struct((y["start"] + s["at"]).alias("start"), y["kind"].alias("kind"), (y["end"] + s["at"]).alias("end"), y["value"].alias("value")))
        return F.struct((s["at"] + x["at"]).alias("at"), F.concat(s["out"], F.array(moved)).alias("out"))

    both = F.zip_with(found, F.slice(gaps, 1, F.size(found)), lambda v, g: F.struct(F.length(g).alias("gap"), v.alias("value")))
    # an array grows by copies: many matches are put together in blocks first, so that the copies stay few
    blocks = F.transform(F.sequence(F.lit(0), F.floor((F.size(both) - 1) / BLOCK).cast("int")), lambda b: F.aggregate(F.slice(both, b * BLOCK + 1, F.lit(BLOCK)), zero, step))
    start = F.struct(F.lit(0).alias("at"), F.array().cast(f"array<{SPANS}>").alias("out"))
    located = F.when(F.size(both) <= BLOCK, F.aggregate(both, zero, step, lambda s: s["out"])).otherwise(F.flatten(F.aggregate(blocks, start, join, lambda s: s["out"])))
    return F.filter(located, keep) if keep else located


def _outside(loose: Column, base: Column, text: Column) -> Column:
    """What base spans leave of each loose span, as spans of at least ``LEAST`` characters."""
    span = lambda a, b: F.struct(a.alias("start"), F.lit(3).alias("kind"), b.alias("end"), F.substring(text, a + 1, b - a).alias("value"))

    def cut(x: Column) -> Column:
        near = F.filter(base, lambda b: (b["start"] < x["end"]) & (x["start"] < b["end"]))
        first = F.struct(x["start"].alias("at"), F.array().cast(SPANS).alias("out"))
        rest = F.aggregate(near, first, lambda s, b: F.struct(F.greatest(s["at"], b["end"]).alias("at"), F.when(b["start"] > s["at"], F.concat(s["out"], F.array(span(s["at"], b["start"])))).otherwise(s["out"]).alias("out")), lambda s: F.when(s["at"] < x["end"], F.concat(s["out"], F.array(span(s["at"], x["end"])))).otherwise(s["out"]))
        return F.when(F.size(near) == 0, F.array(x)).otherwise(rest)

    return F.filter(F.flatten(F.transform(loose, cut)), lambda x: x["end"] - x["start"] >= LEAST)


def secret_spans(docs: DataFrame, text: str = "text", out: str = "spans", table: list[float] | None = None, ratio: float = RATIO) -> DataFrame:
    """Add ``out``: array of struct start, kind, end, value in order of start, then kind (0 assign, 1 access, 2 hex, 3 markov).

    Offsets are code points, ends exclusive. Kinds 0 to 2 are the base patterns, leftmost and non-overlapping for each kind; kind 3 are
    stretches of ``CANDIDATE`` that the Markov models find random, without what base spans cover of them: those with a digit and a letter, or with capitals
    after small letters more than once; words of letters of one case are never judged. Null and empty texts have an empty array. Texts are whole; a
    pattern is only run over texts that hold a character or word without which it cannot match. Rows and other columns stay, but a column named as
    ``out`` is replaced.
    """
    body = F.coalesce(F.col(text), F.lit(""))
    none = F.array().cast(SPANS)
    value = lambda x: F.regexp_extract(x["value"], ASSIGN, 2)
    runs = {
        "assign": F.when(body.contains(":") | body.contains("="), _located(body, ASSIGN, 0, lambda x: F.length(value(x)) >= 6)),
        "access": F.when(body.contains("AKIA"), _located(body, ACCESS, 1, lambda x: F.length(x["value"]) >= 20)),
        # runs of hexadecimal digits are maximal, so asking for 24 at once finds the same runs
        "hex": F.when(body.rlike("[0-9a-f]{24}"), _located(body, "[0-9a-f]{24,}", 2, None)),
        "loose": F.when(body.rlike(MIXED), _located(body, CANDIDATE, 3, lambda x: x["value"].rlike(MIXED))),
    }
    at = dict(zip((*runs, "base"), fresh(docs, *runs, "base")))
    held = docs.select("*", *[F.coalesce(c, none).alias(at[k]) for k, c in runs.items()])
    # a column of its own each, or the optimiser would run the patterns once for each use
    held = held.withColumn(at["base"], F.array_sort(F.concat(at["assign"], at["access"], at["hex"])))
    table = table or train(labelled_samples())
    added = F.filter(_outside(F.col(at["loose"]), F.col(at["base"]), body), lambda x: x["value"].rlike(MIXED) & (markov_ratio(x["value"], table) > ratio))
    spans = F.array_sort(F.concat(at["base"], added))
    return held.select(*[F.col(f"`{c}`") for c in docs.columns if c.lower() != out.lower()], spans.alias(out))


def digest(spans: Column, only: tuple[str, ...] = KINDS) -> Column:
    """kind:start:end of each span of the kinds in ``only``, joined by commas."""
    names = F.array(*[F.lit(k) for k in KINDS])
    kept = F.filter(spans, lambda x: x["kind"] < len(only)) if len(only) < len(KINDS) else spans
    return F.array_join(F.transform(kept, lambda x: F.concat_ws(":", F.get(names, x["kind"]), x["start"].cast("string"), x["end"].cast("string"))), ",")


def count_kind(spans: Column, kind: str) -> Column:
    return F.size(F.filter(spans, lambda x: x["kind"] == KINDS.index(kind))).cast("long")


def redact(docs: DataFrame, text: str = "text", mark: str = "[SECRET]", **models) -> DataFrame:
    """Replace every secret in ``text`` by ``mark``; overlapping spans give one mark. Rows and other columns stay; null stays null."""
    (spans,) = fresh(docs, "spans")
    held = secret_spans(docs, text, spans, **models)
    zero = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))
    cut = lambda a, b: F.substring(F.col(text), a + 1, F.greatest(F.lit(0), b - a))

    def step(s: Column, x: Column) -> Column:
        new = x["start"] >= s["at"]
        return F.struct(F.greatest(s["at"], x["end"]).alias("at"), F.when(new, F.concat(s["out"], cut(s["at"], x["start"]), F.lit(mark))).otherwise(s["out"]).alias("out"))

    rebuilt = F.aggregate(spans, zero, step, lambda s: F.concat(s["out"], cut(s["at"], F.length(F.col(text)))))
    done = F.when(F.size(spans) > 0, rebuilt).otherwise(F.col(text)).alias(text)
    return held.select(*[done if c == text else F.col(f"`{c}`") for c in docs.columns])
