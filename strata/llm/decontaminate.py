"""Benchmark decontamination by pigeonhole edit matching.

Test items are cut into units. A unit with a budget of k errors is split into k + 1
pieces; whatever lies within k edits of the unit holds one of the pieces unchanged and
near its place. So the pieces of all units are searched at once by an Aho-Corasick
automaton, and only the windows that a hit points at are verified, by Myers' bit-parallel
edit distance. Nothing within the budget is missed, and nothing beyond it is reported.

The item table is the query set. Its size is measured first; it goes to the executors in
blocks of bounded size, each of which is searched in all documents.

Items shorter than `shortest` code points have no budget and are found as whole words only,
between blanks or at an end of the text.

Defined results: null and blank texts contain nothing, and null or blank items are in no
document; texts and items are compared
whole, in lower case and with each run of white space as one blank; repeated documents
are each reported, repeated items count by id; empty tables give empty or clean results;
further columns are ignored or, by `clean`, kept.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterable, Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from strata.llm.common import map_texts, worker_cache

#: Bytes of items in one block, at most but for a single longer item.
BLOCK_BYTES = 8_000_000


def plain(text: str | None) -> str:
    return " ".join((text or "").lower().split())


def distance_in(pattern: str, text: str) -> int:
    """The least edit distance of the pattern to any part of the text (Myers, one word of any width)."""
    m = len(pattern)
    if not m:
        return 0
    where: dict[str, int] = {}
    for k, c in enumerate(pattern):
        where[c] = where.get(c, 0) | 1 << k
    full, top = (1 << m) - 1, 1 << m - 1
    plus, minus, score = full, 0, m
    best = score
    for c in text:
        eq = where.get(c, 0)
        x = eq | minus
        d = (((eq & plus) + plus) ^ plus) | x
        up = minus | ~(d | plus) & full
        down = plus & d
        if up & top:
            score += 1
        elif down & top:
            score -= 1
            if score < best:
                best = score
        up = up << 1 & full
        down = down << 1 & full
        plus = down | ~(d | up) & full
        minus = up & d
    return best


def units_of(text: str, longest: int) -> list[str]:
    """Parts of nearly equal length, none over `longest`, cut at blanks where one is near."""
    n = -(-len(text) // longest)
    cuts = [0]
    for k in range(1, n):
        at = k * len(text) // n
        blank = text.rfind(" ", cuts[-1] + 1, at + 1)
        cuts.append(blank if at - blank < 20 and blank > cuts[-1] else at)
    return [text[a:b].strip() for a, b in zip(cuts, [*cuts[1:], len(text)], strict=True)]


class Matcher:
    """All units of a block of items, searched at once."""

    def __init__(self, items: Iterable[tuple[int, str | None]], error_rate: float, longest: int, shortest: int, piece: int):
        import ahocorasick

        self.units: list[tuple[int, str, int]] = []
        pieces: dict[str, list[tuple[int, int]]] = {}
        for item, text in items:
            text = plain(text)
            if not text:
                continue
            for unit in units_of(text, longest) if len(text) >= shortest else [f" {text} "]:
                k = max(0, min(int(error_rate * len(unit)), len(unit) // piece - 1)) if len(text) >= shortest else 0
                cuts = [j * len(unit) // (k + 1) for j in range(k + 2)]
                for a, b in zip(cuts, cuts[1:], strict=False):
                    pieces.setdefault(unit[a:b], []).append((len(self.units), a))
                self.units.append((item, unit, k))
        self.automaton = ahocorasick.Automaton()
        for p, places in pieces.items():
            self.automaton.add_word(p, (len(p), places))
        if pieces:
            self.automaton.make_automaton()
        self.any = bool(pieces)
        self.verified: dict[tuple[int, str], int] = {}

    def find(self, text: str | None) -> dict[int, int]:
        """Items of which a unit lies in the text within its budget, with the least distance."""
        text = f" {plain(text)} "
        if text.isspace() or not self.any:
            return {}
        starts: dict[int, list[int]] = {}
        for end, (n, places) in self.automaton.iter(text):
            for unit, offset in places:
                starts.setdefault(unit, []).append(end + 1 - n - offset)
        found: dict[int, int] = {}
        for number, at in starts.items():
            item, unit, k = self.units[number]
            at.sort()
            first = last = at[0]
            for s in [*at[1:], None]:
                if s is not None and s - last <= 2 * k + 1:
                    last = s
                    continue
                best = self._verify(number, unit, text[max(0, first - k) : max(0, last + len(unit) + k)])
                if best <= k:
                    found[item] = min(best, found.get(item, best))
                first = last = s
        return found

    def _verify(self, number: int, unit: str, window: str) -> int:
        key = (number, window)
        if key not in self.verified:
            if len(self.verified) > 50_000:
                self.verified.clear()
            self.verified[key] = 0 if unit in window else distance_in(unit, window)
        return self.verified[key]


SETTINGS = {"error_rate": 0.08, "longest": 160, "shortest": 24, "piece": 12}


def _matchers(items: DataFrame, item_column: str, item_text: str, settings: dict):
    """For each block of items, a function that gives a worker its matcher."""
    size = items.agg(F.sum(F.octet_length(item_text))).first()[0] or 0
    n_blocks, run = max(1, -(-size // BLOCK_BYTES)), uuid.uuid4().hex
    made = []
    for block in range(n_blocks):
        part = items.filter(F.col(item_column).isNotNull() & (F.pmod(F.xxhash64(item_column, item_text), F.lit(n_blocks)) == block))
        own = items.sparkSession.sparkContext.broadcast(sorted((r[0], r[1] or "") for r in part.select(item_column, item_text).collect()))
        made.append(lambda own=own, block=block: worker_cache("decontamination", f"matcher {run} {block}", lambda: Matcher(own.value, **settings), f"matcher {block}"))
    return made


def find_items(docs: DataFrame, items: DataFrame, id_column: str = "doc_id", text_column: str = "text", item_column: str = "item_id", item_text: str = "text", **settings) -> DataFrame:
    """One row per document: its id, the item_ids it contains (ascending), n_items, the least
    distance (null if none) and contaminated.

    `settings` go over SETTINGS: `error_rate` of a unit's length is its error budget, kept so
    low that pieces have `piece` code points; `longest` bounds a unit.
    """
    kind = docs.schema[id_column].dataType.simpleString()
    d = docs.select(F.col(id_column), F.col(text_column).alias("_text"), F.array().cast("array<long>").alias("item_ids"), F.lit(None).cast("int").alias("distance"))
    for matcher in _matchers(items, item_column, item_text, SETTINGS | settings):

        def kernel(batches: Iterator[dict], matcher=matcher) -> Iterator[dict]:
            own = matcher()
            for b in batches:
                found = [own.find(t) for t in b["_text"]]
                ids = [sorted({*before.tolist(), *f}) for before, f in zip(b["item_ids"], found, strict=True)]
                least = [min((x for x in (before, *f.values()) if x is not None), default=None) for before, f in zip(b["distance"], found, strict=True)]
                yield b | {"item_ids": ids, "distance": least}

        d = map_texts(d, d.columns, kernel, f"{id_column} {kind}, _text string, item_ids array<long>, distance int")
    return d.select(id_column, "item_ids", F.size("item_ids").cast("long").alias("n_items"), "distance", (F.size("item_ids") > 0).alias("contaminated"))


def clean(docs: DataFrame, items: DataFrame, text_column: str = "text", item_column: str = "item_id", item_text: str = "text", **settings) -> DataFrame:
    """The documents that contain no item, with all their columns."""
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    for matcher in _matchers(items, item_column, item_text, SETTINGS | settings):

        def kernel(batches: Iterator[dict], matcher=matcher) -> Iterator[dict]:
            own = matcher()
            for b in batches:
                keep = [k for k, t in enumerate(b[text_column]) if not own.find(t)]
                yield {c: [v[k] for k in keep] for c, v in b.items()}

        docs = map_texts(docs, docs.columns, kernel, schema)
    return docs
