"""The interface that stands for every model call, with offline answers and a cache.

A provider answers a batch: ``complete(frame[key, task, prompt]) -> frame[key, text, ok, error]``. It must be pure, so that a retried
task gives the same rows.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from typing import Protocol

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

ANSWER = "key string, text string, ok boolean, error string"


class Provider(Protocol):
    name: str

    def complete(self, batch: pd.DataFrame) -> pd.DataFrame: ...


#: Words that carry no content of their own; in the invented locale they become endings of the word before them.
PARTICLES = {"of": "un", "than": "dan", "in": "ta", "from": "tan", "to": "a", "with": "la", "by": "ca"}
VERBS = ("list", "show", "count", "find", "give", "rank", "name")
QUESTION = {"how many": "kac", "which": "hangi", "what": "ne", "where": "nerede", "who": "kim"}
BACK, FRONT = "aou", "ei"
HELD = re.compile(r"`[^`]*`|'[^']*'|⟦\d+⟧|\d[\d.,]*")


def harmony(stem: str, ending: str) -> str:
    """The ending's vowels follow the stem's last vowel."""
    front = next((c for c in reversed(stem.lower()) if c in BACK + FRONT), "a") in FRONT
    return ending.translate(str.maketrans("au", "ei")) if front else ending


def invent(text: str) -> str:
    """A sentence in the invented suffixing, verb-final locale. Back-ticked spans, quotes, numbers and placeholders stay as they are."""
    ends = re.search(r"[.?!]*\s*$", text).group()
    body = text[: len(text) - len(ends)] if ends else text
    low = body.lower()
    lead = next((q for q in QUESTION if low.startswith(q)), None)
    if lead:
        body = QUESTION[lead] + body[len(lead) :]
    parts = [p for p in re.split(f"({HELD.pattern})|\\s+", body) if p]
    out: list[str] = []
    pending = None
    for p in parts:
        if HELD.fullmatch(p):
            out.append(p)
            pending = None
        elif p.lower() in PARTICLES and out and not HELD.fullmatch(out[-1]):
            out[-1] += harmony(out[-1], PARTICLES[p.lower()])
        elif p.lower() in ("the", "a", "an"):
            continue
        else:
            out.append(p)
    if out and out[0].lower() in VERBS:
        pending = out.pop(0)
        out.append(pending.lower() + harmony(pending, "yun"))
    return " ".join(out) + ends


class InventedLocaleProvider:
    """Offline: answers text tasks by rule."""

    name = "invented"

    def phrase(self, text: str) -> str:
        """What a fixed phrase, such as a cue of comparison, becomes within a sentence."""
        return invent(f"x {text} x").removeprefix("x ").removesuffix(" x")

    def complete(self, batch: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"key": batch["key"], "text": [invent(p) for p in batch["prompt"]], "ok": True, "error": None})


class EchoProvider:
    """Answers with the prompt itself."""

    name = "echo"

    def complete(self, batch: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"key": batch["key"], "text": batch["prompt"], "ok": True, "error": None})


class ReplayProvider:
    """Answers from a given mapping of keys to texts, so that outputs of a real model can be scored without calling it."""

    name = "replay"

    def __init__(self, answers: dict[str, str]):
        self.answers = answers

    def complete(self, batch: pd.DataFrame) -> pd.DataFrame:
        texts = [self.answers.get(k) for k in batch["key"]]
        return pd.DataFrame({"key": batch["key"], "text": texts, "ok": [t is not None for t in texts], "error": [None if t is not None else "no answer" for t in texts]})


class RemoteProvider:
    """HTTP endpoint that takes {"task", "prompt"} and returns {"text"}; never called unless built with a URL."""

    name = "remote"

    def __init__(self, url: str, timeout: float = 60.0, retries: int = 3):
        self.url, self.timeout, self.retries = url, timeout, retries

    def complete(self, batch: pd.DataFrame) -> pd.DataFrame:
        import json
        import urllib.request

        rows = []
        for r in batch.itertuples(index=False):
            text, error = None, None
            for _ in range(self.retries):
                try:
                    call = urllib.request.Request(self.url, json.dumps({"task": r.task, "prompt": r.prompt}).encode(), {"Content-Type": "application/json"})
                    with urllib.request.urlopen(call, timeout=self.timeout) as answer:  # noqa: S310
                        text, error = json.load(answer)["text"], None
                    break
                except (OSError, ValueError, KeyError) as e:
                    error = str(e)
            rows.append((r.key, text, text is not None, error))
        return pd.DataFrame(rows, columns=["key", "text", "ok", "error"])


def prompt_key(task: str, prompt: str, config: str = "") -> str:
    return hashlib.md5("\x1f".join((task, prompt, config)).encode()).hexdigest()


def complete(prompts: DataFrame, provider: Provider, config: str = "", cache: DataFrame | None = None, batch: int = 256) -> DataFrame:
    """Answers (key, text, ok, error) of distinct prompts (task, prompt). Prompts whose key is in ``cache`` make no call."""
    keyed = prompts.select("task", "prompt").distinct().withColumn("key", F.md5(F.concat_ws("\x1f", "task", "prompt", F.lit(config))))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for k in range(0, len(frame), batch):
                yield provider.complete(frame.iloc[k : k + batch])[["key", "text", "ok", "error"]]

    todo = keyed if cache is None else keyed.join(cache.select("key"), "key", "left_anti")
    made = todo.mapInPandas(run, ANSWER)
    return made if cache is None else made.unionByName(cache.join(keyed, "key", "left_semi").select("key", "text", "ok", "error"))
