"""Token counts by a compiled transducer over characters.

A BPE vocabulary with word ends is compiled, on demand, into one deterministic
transducer that reads characters and emits token counts on its transitions:

* its scanner part splits letters, numbers, other signs and contractions;
* its merge part rests on the fact that a sequence of tokens is the BPE encoding of
  its bytes exactly when every two neighbours are what BPE makes of their joined bytes.
  So each prefix has one last token, and the state needs only, for each suffix that is
  still a proper beginning of some token, the last token before it and how many tokens
  lie between. Counts are kept relative, so states repeat and can be tabulated.

A piece of text is then a map from entry states to (exit state, count). Such maps
compose associatively; the maps of a text's chunks are joined by a prefix scan. White
space brings the machine back to its start, so in a chunk's map only what stands before
the first white space depends on the entry; the words within are whole, and the count of
each is kept by its spelling. Tables are dropped between sections of chunks when they are
full, and the state that leads into the next section is carried over.

Defined results: null and empty texts have no tokens; texts of any length are counted
whole; repeated rows are counted each; an empty table gives an empty result; further
columns of the input are ignored.
"""

from __future__ import annotations

import json
import re
import unicodedata
from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from strata.llm.common import map_texts, worker_cache

#: Unicode white space, as the tokenizer's pattern has it.
WHITE = "\x09\x0a\x0b\x0c\x0d\x20\x85\xa0\u1680\u2000\u2001\u2002\u2003\u2004\u2005\u2006\u2007\u2008\u2009\u200a\u2028\u2029\u202f\u205f\u3000"
#: Entries after which a worker's tables are dropped and built anew.
MOST_STATES, MOST_WORDS = 400_000, 600_000
#: Code points of one chunk of a text, and chunks that are scanned together.
CHUNK, SECTION = 2048, 64


def byte_letters() -> list[str]:
    """The printable stand-ins of bytes in byte-level vocabularies."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    letters, extra = {b: chr(b) for b in shown}, 0
    for b in range(256):
        if b not in letters:
            letters[b] = chr(256 + extra)
            extra += 1
    return [letters[b] for b in range(256)]


class Merges:
    """BPE of one word by ranks: the definition that the transducer is compiled from."""

    def __init__(self, spec: dict):
        model = spec["model"]
        self.suffix = model["end_of_word_suffix"] or ""
        pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        self.rank = {p: k for k, p in enumerate(pairs)}
        self.vocab = set(model["vocab"])
        self.special = sorted((t["content"] for t in spec.get("added_tokens", [])), key=len, reverse=True)
        self.splits: dict[str, tuple[str, ...]] = {}
        for left, right in pairs:  # a token's last merge, as BPE itself would do it
            self.splits.setdefault(left + right, (left, right))

    def encode(self, symbols: list[str]) -> list[str]:
        out, rank = list(symbols), self.rank
        while len(out) > 1:
            best = min((rank.get((out[k], out[k + 1]), 1 << 60), k) for k in range(len(out) - 1))
            if best[0] == 1 << 60:
                break
            k = best[1]
            out[k : k + 2] = [out[k] + out[k + 1]]
        return out


class Transducer:
    """States are numbered as they are met. `step[s][c]` is (next state, tokens emitted)."""

    def __init__(self, vocabulary: str):
        self.merges = Merges(json.loads(vocabulary))
        self.letters = byte_letters()
        self.trie: list[dict[str, int]] = [{}]
        self.token: list[str | None] = [None]
        for word in self.merges.vocab:
            at = 0
            for symbol in self.symbols(word):
                if symbol not in self.trie[at]:
                    self.trie[at][symbol] = len(self.trie)
                    self.trie.append({})
                    self.token.append(None)
                at = self.trie[at][symbol]
            self.token[at] = word
        self.pairs: dict[tuple[str, str], bool] = {}
        self.reset()

    def reset(self) -> None:
        """Empty tables, of the merge part and of the whole."""
        self.merge_id: dict = {}
        self.merge_state: list = []
        self.merge_step: list[dict[int, tuple[int, int]]] = []
        self.state_id: dict = {}
        self.states: list = []
        self.step: list[dict[str, tuple[int, int]]] = []
        self.final: list[int] = []
        self.word_start = self._merge(((0, None, 0),), 0)
        self.start = self._state("start", None)
        self.words: dict[str, int] = {}

    def symbols(self, token: str) -> list[str]:
        """A vocabulary entry as start symbols; the last carries the word end if the token has it."""
        end = self.merges.suffix
        if end and token.endswith(end) and len(token) > len(end):
            body = token[: -len(end)]
            return [*body[:-1], body[-1] + end]
        return list(token)

    # The merge part: one word, byte by byte.

    def _merge(self, live: tuple, ending: int) -> int:
        key = (live, ending)
        if key not in self.merge_id:
            self.merge_id[key] = len(self.merge_state)
            self.merge_state.append(key)
            self.merge_step.append({})
        return self.merge_id[key]

    def fits(self, left: str | None, right: str) -> bool:
        if left is None:
            return True
        key = (left, right)
        if key not in self.pairs:
            if len(self.pairs) > 2_000_000:
                self.pairs.clear()
            self.pairs[key] = self.merges.encode(self.symbols(left) + self.symbols(right)) == [left, right]
        return self.pairs[key]

    def whole(self, token: str) -> bool:
        """BPE gives this entry for its own symbols; entries that no merge order reaches never appear."""
        key = (token, "")
        if key not in self.pairs:
            self.pairs[key] = self.merges.encode(self.symbols(token)) == [token]
        return self.pairs[key]

    def _last(self, live: tuple, symbol: str) -> tuple[str, int] | None:
        """The last token when `symbol` ends the prefix, and its count; long tokens are tried first."""
        for node, before, count in live:
            below = self.trie[node].get(symbol)
            if below is not None and (t := self.token[below]) is not None and self.whole(t) and self.fits(before, t):
                return t, count + 1
        return None

    def merge_next(self, state: int, byte: int) -> tuple[int, int]:
        """(state after the byte, tokens emitted); what a word end here would add is in the state."""
        found = self.merge_step[state].get(byte)
        if found is None:
            live, _ = self.merge_state[state]
            letter = self.letters[byte]
            inner, last = self._last(live, letter), self._last(live, letter + self.merges.suffix)
            grown = [(self.trie[n][letter], b, c) for n, b, c in live if letter in self.trie[n]]
            token, count = inner
            grown = [x for x in grown if self.trie[x[0]]] + [(0, token, count)]
            found = self.merge_step[state][byte] = (self._merge(tuple((n, b, c - count) for n, b, c in grown), last[1] - count), count)
        return found

    # The whole machine. A state is (scanner mode, merge state).

    def _state(self, mode: str, merge) -> int:
        key = (mode, merge)
        if key not in self.state_id:
            self.state_id[key] = len(self.states)
            self.states.append(key)
            self.step.append({})
            self.final.append(self._pending(mode, merge))
        return self.state_id[key]

    def _bytes(self, merge: int, text: str) -> tuple[int, int]:
        count = 0
        for byte in text.encode("utf-8", "surrogatepass"):
            merge, n = self.merge_next(merge, byte)
            count += n
        return merge, count

    def _word(self, text: str) -> int:
        merge, count = self._bytes(self.word_start, text)
        return count + self.merge_state[merge][1]

    def _pending(self, mode: str, merge) -> int:
        """Tokens that are still owed if the text ends in this state."""
        if mode == "start":
            return 0
        if mode in ("letters", "signs"):
            return self.merge_state[merge][1]
        return self._word(mode[0]) + (self._word(mode[1:]) if len(mode) > 1 else 0)

    def next(self, state: int, c: str) -> tuple[int, int]:
        found = self.step[state].get(c)
        if found is None:
            found = self.step[state][c] = self._compute(state, c)
        return found

    def _begin(self, c: str, kind: str, owed: int) -> tuple[int, int]:
        """The state after a first character of a new word, when `owed` tokens are due for what came before."""
        if kind == "white":
            return self.start, owed
        if kind == "number":
            return self.start, owed + self._word(c)
        if c == "'":
            return self._state("'", None), owed
        merge, count = self._bytes(self.word_start, c)
        return self._state("letters" if kind == "letter" else "signs", merge), owed + count

    def _compute(self, state: int, c: str) -> tuple[int, int]:
        mode, merge = self.states[state]
        major = unicodedata.category(c)[0]
        kind = "white" if c in WHITE else "letter" if major == "L" else "number" if major == "N" else "sign"
        if mode[0] == "'":
            if mode == "'" and c in "stmd" or mode + c in ("'re", "'ve", "'ll"):
                return self.start, self._word(mode + c)
            if mode == "'" and c in "rvl":
                return self._state(mode + c, None), 0
            if mode == "'" and kind == "sign":  # a run of signs that began with the apostrophe
                merge, count = self._bytes(self.word_start, "'" + c)
                return self._state("signs", merge), count
            if len(mode) > 1 and kind == "letter":
                merge, count = self._bytes(self.word_start, mode[1] + c)
                return self._state("letters", merge), self._word("'") + count
            return self._begin(c, kind, self._pending(mode, merge))
        if mode == "letters" and kind == "letter" or mode == "signs" and kind == "sign":
            merge, count = self._bytes(merge, c)
            return self._state(mode, merge), count
        return self._begin(c, kind, self._pending(mode, merge))

    # Maps of chunks and their composition.

    def run(self, state: int, text: str, meet: list[int] | None = None) -> tuple[int, int, list[int]]:
        """(exit state, tokens, states on the way). It stops early, with exit -1, where it meets the path `meet`."""
        step, count, path = self.step, 0, []
        for k, c in enumerate(text):
            found = step[state].get(c) or self.next(state, c)
            state = found[0]
            count += found[1]
            path.append(state)
            if meet is not None and meet[k] == state:
                return -1, count, path
        return state, count, path

    def carry(self, state: int) -> int:
        """The state's number in tables that are begun anew."""
        mode, merge = self.states[state]
        key = None if merge is None else self.merge_state[merge]
        self.reset()
        return self._state(mode, None if key is None else self._merge(*key))

    def word(self, word: str) -> int:
        """Tokens of a run between white space, of any length."""
        n = self.words.get(word)
        if n is None:
            state, n, _ = self.run(self.start, word)
            n += self.final[state]
            if len(word) <= 64:
                if len(self.words) >= MOST_WORDS:
                    self.words.clear()
                self.words[word] = n
        return n

    def count(self, text: str) -> int:
        """Tokens of a text that is already normalised."""
        state, count = self.start, 0
        for a in range(0, len(text), CHUNK * SECTION):
            maps = [ChunkMap(self, text[k : k + CHUNK]) for k in range(a, min(len(text), a + CHUNK * SECTION), CHUNK)]
            state, n = scan(maps, state)[-1] if len(maps) > 1 else maps[0](state)
            count += n
            if len(self.states) > MOST_STATES or len(self.merge_state) > MOST_STATES:
                state = self.carry(state)
        return count + self.final[state]


WHITE_RUN, ODD = re.compile(f"[{WHITE}]+"), re.compile(r"[\x1c-\x1f]")


class ChunkMap:
    """Entry state to (exit state, tokens) of one chunk.

    Up to the first white space the entry matters; what follows is one number, and the exit is that of the last run.
    In a chunk without white space the path from the start state is kept; other entries run only until they meet it,
    after which both go on alike."""

    def __init__(self, machine: Transducer, text: str):
        self.machine, self.text, self.known = machine, text, {}
        self.path: list[int] | None = None
        self.emitted: list[int] | None = None
        words = WHITE_RUN.split(text) if ODD.search(text) else text.split()
        self.head = text
        if not words or len(words) > 1 or text[0] in WHITE or text[-1] in WHITE:
            if words and text[0] in WHITE and words[0]:
                words.insert(0, "")
            if words and text[-1] in WHITE and words[-1]:
                words.append("")
            self.head = words[0] if words else ""
            known = machine.words
            try:
                within = sum(map(known.__getitem__, words[1:-1]))
            except KeyError:
                within = sum(map(machine.word, words[1:-1]))
            self.exit, n, _ = machine.run(machine.start, words[-1] if words else "")
            self.rest = within + n
        else:
            self.exit = None

    def __call__(self, entry: int) -> tuple[int, int]:
        if entry not in self.known:
            self.known[entry] = self._through(entry) if self.exit is None else self._into_white(entry)
        return self.known[entry]

    def _into_white(self, entry: int) -> tuple[int, int]:
        machine = self.machine
        if entry == machine.start:
            return self.exit, machine.word(self.head) + self.rest if self.head else self.rest
        state, n, _ = machine.run(entry, self.head)
        return self.exit, n + machine.final[state] + self.rest

    def _through(self, entry: int) -> tuple[int, int]:
        machine = self.machine
        if self.path is None:
            exit_, count, self.path = machine.run(machine.start, self.text)
            self.known[machine.start] = (exit_, count)
        if entry == machine.start:
            return self.known[entry]
        exit_, count, path = machine.run(entry, self.text, self.path)
        if exit_ < 0:
            if self.emitted is None:
                total, state, self.emitted = 0, machine.start, []
                for c, after in zip(self.text, self.path, strict=True):
                    total += machine.step[state][c][1]
                    self.emitted.append(total)
                    state = after
            exit_, whole = self.known[machine.start]
            count += whole - self.emitted[len(path) - 1]
        return exit_, count


class Composed:
    """The map of two neighbouring pieces, itself a map."""

    def __init__(self, first, second):
        self.first, self.second, self.known = first, second, {}

    def __call__(self, entry: int) -> tuple[int, int]:
        if entry not in self.known:
            middle, a = self.first(entry)
            exit_, b = self.second(middle)
            self.known[entry] = (exit_, a + b)
        return self.known[entry]


def scan(maps: list, start: int) -> list[tuple[int, int]]:
    """(state, tokens so far) after each chunk, by an inclusive prefix scan in log2(n) rounds of pairwise composition."""
    prefix, reach = list(maps), 1
    while reach < len(prefix):
        prefix = [m if k < reach else Composed(prefix[k - reach], m) for k, m in enumerate(prefix)]
        for m in prefix:
            m(start)
        reach *= 2
    return [m(start) for m in prefix]


def normalise(text: str) -> str:
    """NFC and lower case, character by character: a final sigma is a sigma like any other."""
    if not text.isascii():
        text = unicodedata.normalize("NFC", text)
        if "Σ" in text:
            text = text.replace("Σ", "σ")
    return text.lower()


class Counter:
    """Whole texts, with the library's treatment of special strings."""

    def __init__(self, vocabulary: str):
        self.machine = Transducer(vocabulary)
        special = self.machine.merges.special
        self.special = re.compile("|".join(map(re.escape, special))) if special else None

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if self.special and "<|" in text:
            parts = self.special.split(text)
            return len(parts) - 1 + sum(self.machine.count(normalise(p)) for p in parts)
        return self.machine.count(normalise(text))


def count_tokens(docs: DataFrame, vocabulary_path: str, limit: int, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """One row per document: its id, n_bytes, n_tokens and whether n_tokens is over `limit`."""
    with open(vocabulary_path, encoding="utf-8") as f:
        vocabulary = docs.sparkSession.sparkContext.broadcast(f.read())
    kind = docs.schema[id_column].dataType.simpleString()

    def kernel(batches: Iterator[dict]) -> Iterator[dict]:
        counter = worker_cache("token counts", f"token counter {vocabulary_path}", lambda: Counter(vocabulary.value))
        for b in batches:
            yield {id_column: b[id_column], "n_bytes": [n or 0 for n in b["n_bytes"]], "n_tokens": [counter.count(t) for t in b[text_column]]}

    sized = docs.select(id_column, text_column, F.octet_length(text_column).cast("long").alias("n_bytes"))
    counted = map_texts(sized, [id_column, text_column, "n_bytes"], kernel, f"{id_column} {kind}, n_bytes long, n_tokens long")
    return counted.withColumn("over_limit", F.col("n_tokens") > limit)
