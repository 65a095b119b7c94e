"""record_prompt_cleaner: one prompted completion per distinct record, through a pluggable completer.

A completer maps prompts to JSON texts. Prompts are deduplicated by the record's hash, so cost follows the number of
distinct records, not of rows. RulebookCompleter is a deterministic stand-in without network: it knows the public
dictionaries and each column's format, judges every record on its own, knows nothing of how errors or records are made,
and is not a language model.
"""

from __future__ import annotations

import html
import json
import re
from collections.abc import Iterator
from dataclasses import dataclass
from typing import Protocol

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellscrub.functions.dicts import ABBREVIATIONS, ALIASES, accent_table
from cellscrub.schema import ATTRS

# What one call costs at about 650 dollars for 4.3 million records; a common length of a token.
DOLLARS_PER_CALL = 0.00015
CHARACTERS_PER_TOKEN = 4

DESCRIPTIONS = {
    "name": "name of the place", "house_number": "house number, may end in a letter", "road": "street with its type in full", "postcode": "five digits",
    "locality": "town", "region": "part of the country", "country": "country name in full", "country_code": "two capital letters",
}
RULES = "Values are written in full, in title case, without abbreviations, in the local standard language. A country has one code."


class Completer(Protocol):
    def complete(self, prompts: list[str]) -> list[str]: ...


FORMATS = {"house_number": r"\d+[a-z]?", "postcode": r"\d{5}", "country_code": r"[A-Z]{2}"}
_FOLD = str.maketrans(*accent_table())


@dataclass(frozen=True)
class RulebookCompleter:
    """Offline profile: `strict` also distrusts values with digits or marks where the column has none. failing: share of
    prompts answered with broken JSON."""

    profile: str = "plain"
    failing: int = 0

    def complete(self, prompts: list[str]) -> list[str]:
        return [self._one(p, i) for i, p in enumerate(prompts)]

    def _one(self, prompt: str, i: int) -> str:
        if self.failing and i % 100 < self.failing:
            return "{broken"
        record = json.loads(prompt.rpartition("RECORD ")[2])
        return json.dumps({a: self._cell(a, record.get(a)) for a in ATTRS})

    def _cell(self, attr: str, value: str | None) -> dict:
        if value is None or not value.strip():
            return {"error": True, "value": None}
        fixed = html.unescape(value).strip()
        if attr in FORMATS:
            bare = re.sub(r"[^0-9A-Za-z]", "", fixed)
            bare = bare.upper() if attr == "country_code" else bare.lower()
            good = re.fullmatch(FORMATS[attr], bare) is not None
            return {"error": fixed != bare or fixed != value or not good, "value": bare if good and bare != value else None}
        words = [_written_out(w) for w in re.sub(r"[-_]+", " ", fixed).rstrip(".,;").split()]
        fixed = " ".join(words)
        if fixed == fixed.upper() or fixed == fixed.lower():
            fixed = fixed.title()
        odd = self.profile == "strict" and attr != "name" and re.search(r"[^\w .']", fixed) is not None
        return {"error": fixed != value or odd, "value": fixed if fixed != value else None}


def _written_out(word: str) -> str:
    """A word's long English form, where the dictionaries have exactly one."""
    plain = word.rstrip(".").lower().translate(_FOLD)
    long = ABBREVIATIONS.get(plain, ())
    known = long[0] if len(long) == 1 else ALIASES.get(plain)
    return known.capitalize() if known else word


def head(task: str) -> str:
    """What stands before the record in every prompt."""
    return f"TASK {task}\nRULES {RULES}\n" + "\n".join(f"COLUMN {a}: {d}" for a, d in DESCRIPTIONS.items()) + "\nRECORD "


def prompts(dirty: DataFrame, task: str = "correct") -> DataFrame:
    """key and prompt of every distinct record; the record stands last, as JSON."""
    keyed = with_key(dirty)
    return keyed.dropDuplicates(["key"]).select("key", F.concat(F.lit(head(task)), F.to_json(F.struct(*ATTRS), {"ignoreNullFields": "false"})).alias("prompt"))


def with_key(dirty: DataFrame) -> DataFrame:
    return dirty.withColumn("key", F.md5(F.concat_ws("\x1f", *[F.coalesce(F.col(a), F.lit("\x00")) for a in ATTRS])))


ANSWER = "map<string, struct<error: boolean, value: string>>"


def answers(dirty: DataFrame, completer: Completer, task: str = "correct", batch: int = 64, retries: int = 1) -> DataFrame:
    """key, answer (map, null where the JSON was bad), calls, characters sent."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for at in range(0, len(frame), batch):
                part = frame.iloc[at : at + batch]
                replies, calls = completer.complete(list(part["prompt"])), [1] * len(part)
                for i, p in enumerate(part["prompt"]):
                    for _ in range(retries):
                        if replies[i].startswith("{") and replies[i].endswith("}"):
                            break
                        replies[i] = completer.complete([p])[0]
                        calls[i] += 1
                yield pd.DataFrame({"key": part["key"], "reply": replies, "calls": calls, "characters": [c * len(p) for c, p in zip(calls, part["prompt"])]})

    raw = prompts(dirty, task).mapInPandas(run, "key string, reply string, calls int, characters long")
    return raw.select("key", F.from_json("reply", ANSWER).alias("answer"), "calls", "characters")


def repairs(dirty: DataFrame, completer: Completer = RulebookCompleter(), task: str = "correct") -> DataFrame:
    """_id, attr, error, repair for all cells of answered records."""
    found = answers(dirty, completer, task).filter(F.col("answer").isNotNull()).select("key", F.explode("answer").alias("attr", "a"))
    return with_key(dirty).select("_id", "key").join(found, "key").select("_id", "attr", F.col("a.error").alias("error"), F.col("a.value").alias("repair"))


def detect(dirty: DataFrame, completer: Completer = RulebookCompleter()) -> DataFrame:
    return repairs(dirty, completer, "detect").filter("error").select("_id", "attr")


def correct(dirty: DataFrame, cells: DataFrame, completer: Completer = RulebookCompleter()) -> DataFrame:
    got = repairs(dirty, completer).filter(F.col("repair").isNotNull())
    return got.join(cells.select("_id", "attr"), ["_id", "attr"], "left_semi").select("_id", "attr", "repair", F.lit(1.0).alias("score"))


def cost(dirty: DataFrame, completer: Completer = RulebookCompleter(), task: str = "correct") -> DataFrame:
    """rows, calls, bad_json, tokens sent (by the prompts' length) and dollars of one run."""
    got = answers(dirty, completer, task).agg(F.sum("calls").alias("calls"), F.sum("characters").alias("characters"), F.count_if(F.col("answer").isNull()).alias("bad_json"))
    rows = dirty.agg(F.count("*").alias("n_rows"))
    return rows.crossJoin(F.broadcast(got)).select("n_rows", "calls", "bad_json", F.ceil(F.col("characters") / CHARACTERS_PER_TOKEN).alias("tokens"), F.round(F.col("calls") * DOLLARS_PER_CALL, 6).alias("dollars"))
