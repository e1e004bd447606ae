"""Secret scanning: fixed rules, and two character Markov models compared by log-likelihood ratio.

The rules find assignments, access keys and long hexadecimal runs. Beyond them, every
long run of token characters is scored under a model of random strings and under a
model of ordinary words and identifiers; a run whose ratio is over the threshold is a
span of kind `random`, unless it overlaps a rule's span.

Defined results: null counts as the empty text, which has no spans; texts are scanned
whole; repeated rows are scanned each; an empty table gives an empty result; columns
of the input other than id and text are not read. Offsets count code points.
"""

from __future__ import annotations

import math
import random
import re
from collections.abc import Iterable, Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from strata.llm.common import map_texts

#: The rules, and the order of their kinds.
ASSIGN = re.compile(r"""(?ai:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex", "random")

RUN = re.compile(r"[A-Za-z0-9+/_=-]{16,}")
SYMBOLS = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-"

Span = tuple[str, int, int]


def rule_spans(text: str) -> list[Span]:
    found: list[Span] = []
    if "=" in text or ":" in text:
        found += [("assign", *m.span()) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    if "AKIA" in text:
        found += [("access", *m.span()) for m in ACCESS.finditer(text) if len(m[0]) >= 20]
    found += [("hex", *m.span()) for m in HEX.finditer(text)]
    return in_order(found)


def in_order(spans: Iterable[Span]) -> list[Span]:
    return sorted(spans, key=lambda s: (s[1], KINDS.index(s[0]), s[2]))


class MarkovRatio:
    """First-order models over `SYMBOLS`, fitted by counting with a constant added to each transition."""

    def __init__(self, random_samples: Iterable[str], ordinary_samples: Iterable[str], added: float = 0.2):
        one, other = self._fit(random_samples, added), self._fit(ordinary_samples, added)
        self.gain = {pair: one[pair] - other[pair] for pair in one}

    @staticmethod
    def _fit(samples: Iterable[str], added: float) -> dict[str, float]:
        count = dict.fromkeys((a + b for a in "^" + SYMBOLS for b in SYMBOLS), added)
        for s in samples:
            for k in range(len(s)):
                pair = (s[k - 1] if k else "^") + s[k]
                if pair in count:
                    count[pair] += 1
        row = {a: sum(count[a + b] for b in SYMBOLS) for a in "^" + SYMBOLS}
        return {pair: math.log(n / row[pair[0]]) for pair, n in count.items()}

    def score(self, run: str) -> float:
        """Nats per character in favour of a random string."""
        gain = self.gain
        return (gain["^" + run[0]] + sum(gain[run[k : k + 2]] for k in range(len(run) - 1))) / len(run)


def random_strings(n: int, seed: int = 7) -> list[str]:
    """Labelled samples of the one class: `n` draws for each of five alphabets that keys are written in."""
    draw = random.Random(seed)
    alphabets = ("0123456789abcdef", "0123456789ABCDEF", SYMBOLS[:62], SYMBOLS[:64], SYMBOLS[:26] + "234567")
    return ["".join(draw.choices(a, k=draw.randint(16, 48))) for a in alphabets for _ in range(n)]


def ordinary_strings(docs: DataFrame, n_docs: int, n_words: int, id_column: str = "doc_id", text_column: str = "text") -> list[str]:
    """Labelled samples of the other class: at most `n_words` words of at most `n_docs` documents, in three
    cases and joined as identifiers, and numbers. Both bounds are parameters; which rows are taken depends on hashes only."""
    ids = docs.select(id_column).distinct().orderBy(F.xxhash64(id_column), id_column).limit(n_docs)
    words = docs.join(ids, id_column, "left_semi").select(F.explode(F.array_distinct(F.split(text_column, "[^A-Za-z]+"))).alias("word"))
    taken = words.filter(F.length("word").between(4, 40)).distinct().orderBy(F.xxhash64("word"), "word").limit(n_words)
    own = [r.word for r in taken.collect()]
    joined = [sep.join(own[k : k + 3]) for k, sep in zip(range(0, len(own) - 2, 3), ["_", "-", "/"] * len(own))]
    camel = ["".join(w.capitalize() for w in own[k : k + 3]) for k in range(0, len(own) - 2, 3)]
    draw = random.Random(11)
    numbers = ["".join(draw.choices("0123456789", k=draw.randint(8, 20))) for _ in range(max(200, n_words // 5))]
    rules = ["=" * 40, "-" * 40, "_" * 40, "+" * 40, "/" * 40] * 20
    return [*own, *(w.upper() for w in own), *(w.capitalize() for w in own), *(w.lower() for w in own), *joined, *camel, *numbers, *rules]


def fit(docs: DataFrame, n_docs: int = 400, n_words: int = 20_000, n_random: int = 3_000) -> MarkovRatio:
    """The two models, from bounded labelled samples."""
    return MarkovRatio(random_strings(n_random), ordinary_strings(docs, n_docs, n_words))


def method_spans(text: str, model: MarkovRatio, threshold: float, rules: list[Span]) -> list[Span]:
    found = []
    for m in RUN.finditer(text):
        if model.score(m[0]) > threshold:
            start, end = m.span()
            if not any(a < end and start < b for _, a, b in rules):
                found.append(("random", start, end))
    return found


def scan_secrets(docs: DataFrame, model: MarkovRatio, threshold: float = 0.7, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """One row per document: its id and `spans`, an array of (kind, start, end) by start, then kind."""
    kind = docs.schema[id_column].dataType.simpleString()

    def kernel(batches: Iterator[dict]) -> Iterator[dict]:
        for b in batches:
            spans = []
            for text in b[text_column]:
                rules = rule_spans(text or "")
                spans.append([{"kind": k, "start": s, "end": e} for k, s, e in in_order(rules + method_spans(text or "", model, threshold, rules))])
            yield {id_column: b[id_column], "spans": spans}

    return map_texts(docs, [id_column, text_column], kernel, f"{id_column} {kind}, spans array<struct<kind: string, start: int, end: int>>")


def redact(docs: DataFrame, model: MarkovRatio, threshold: float = 0.7, mark: str = "[SECRET]", text_column: str = "text") -> DataFrame:
    """The documents with every span replaced by `mark`; overlapping spans get one mark. All columns stay."""
    names, schema = docs.columns, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)

    def kernel(batches: Iterator[dict]) -> Iterator[dict]:
        for b in batches:
            texts = []
            for text in b[text_column]:
                if text:
                    rules = rule_spans(text)
                    out, at = [], 0
                    for _, s, e in in_order(rules + method_spans(text, model, threshold, rules)):
                        if s >= at:
                            out += [text[at:s], mark]
                        at = max(at, e)
                    text = "".join(out) + text[at:] if out else text
                texts.append(text)
            yield b | {text_column: texts}

    return map_texts(docs, names, kernel, schema)


def digest(spans, kinds: tuple[str, ...]):
    """`kind:start:end` of the spans of these kinds, comma-joined."""
    own = F.filter(spans, lambda s: s["kind"].isin(*kinds)) if kinds != KINDS else spans
    return F.array_join(F.transform(own, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
