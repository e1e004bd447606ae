"""Language-model scoring by logistic context mixing over the bits of a word code.

A text is its words, each coded by a prefix code (frequent words are short), and its end,
which is the empty word. A word outside the code is an escape, spelled by its bytes and an
end byte. So a text is a row of bits, and the probabilities of all texts add up to at most
one. Each bit of a word is predicted from

* the frequencies of the words below either branch of the code,
* a table of counts by the word before, hashed;

each bit of a spelled byte from counts by the last two bytes and by all of the word so far. A mixer combines the predictions in the logistic domain with weights from a
set that a gate picks by what the contexts have seen and how deep in the code the bit lies; a
table then refines the result by the gate. Ahead of all this, one bit says whether the word is
the one that a table keeps, for the two words before, hashed, as what followed them most; its
probability goes by how far that word leads. Where it says no, that word's own place in the
code is left unused.

All of it is learned online, in one pass over all training texts: each stretch of a
partition is predicted from what came before, the mixer and the refining table learn from
the errors, and the counts are added. Partitions' counts are added up, their followers
meet by majority, and their weights are averaged in a fixed order. The tables' sizes follow
the number of distinct words; `most_slots` bounds them to what a worker can hold, and
contexts share slots from there on. Then everything stands still, so a text's score depends
on that text alone and a lost executor's work can be repeated. Another split of the input
into partitions gives slightly other weights and followers.

Defined results: a null text is empty and has the end token only; texts are taken whole;
a null id counts as the empty string when its fold is found; repeated rows are each
learned from and scored; an empty table gives an empty result; further columns are
ignored.
"""

from __future__ import annotations

import math
import uuid
import zlib
from array import array
from collections.abc import Iterable, Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from strata.llm.common import give_back, map_texts, materialize, release, worker_cache
from strata.llm.near_dup import LOWER

#: Odd factors of the hashes.
ODD = (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB, 0xD6E8FEB86659FD93)
#: Words of a stretch that is predicted at once, and bits of a batch that the mixer learns from at once.
STRETCH, BATCH = 16_384, 8192
#: Inputs of the mixer, sets of weights (of words' bits, then of bytes' bits), and places of the refining table.
INPUTS, WORD_SETS, BYTE_SETS, APM = 2, 12, 16, 33
SETS = WORD_SETS + BYTE_SETS
#: Levels of the code that are predicted from contexts; below, a word's frequency alone decides.
DEEP = 9
#: Words with counts that a task holds before it sums them up, and hands them on if they stay over half of it.
MOST_HELD = 800_000
#: The bit that stands where a word has no more bits.
NONE = 2
#: Slots of one block of counts, and least and most log2 of the slots of a table.
BLOCK, LEAST_BITS = 1 << 16, 12
#: The number that stands for a task's mixer among the blocks.
MIXERS = 1 << 30


def tokens(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(LOWER).split()


def ranges(texts: list[str | None], most: int = 4_000_000) -> Iterator[slice]:
    """Runs of texts that hold about `most` code points, so that what is made of them stays small."""
    first = size = 0
    for k, t in enumerate(texts):
        size += len(t or "")
        if size >= most or k == len(texts) - 1:
            yield slice(first, k + 1)
            first, size = k + 1, 0


def split(texts: list[str | None]):
    """All words of the texts, one after another, as an Arrow array of bytes, and how many each text has: `tokens` of many
    texts at once."""
    import numpy as np
    import pyarrow as pa
    import pyarrow.compute as pc

    lists = pc.ascii_split_whitespace(pc.ascii_trim_whitespace(pc.ascii_lower(pa.array([t or "" for t in texts], pa.large_string()))))
    flat, ends = lists.flatten(), lists.offsets.to_numpy()
    lengths = np.diff(ends)
    empty = (lengths == 1) & (pc.binary_length(flat.take(pa.array(np.minimum(ends[:-1], max(0, len(flat) - 1))))).to_numpy() == 0) if len(flat) else lengths == 1
    if empty.any():  # a blank text gives one empty word
        keep = np.ones(len(flat), bool)
        keep[ends[:-1][empty]] = False
        flat, lengths = flat.filter(pa.array(keep)), lengths - empty
    return flat.cast(pa.large_binary()), lengths


class Code:
    """A prefix code of least length over the given words and an escape, which is the last symbol."""

    def __init__(self, words: Iterable[bytes], counts: Iterable[int], escapes: int):
        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc

        counts = np.asarray(counts, np.float64)
        n = len(counts) + 1
        self.escape = n - 1
        self.words = pa.array(words, pa.large_binary())
        self.end = next(iter(pc.indices_nonzero(pc.equal(self.words, b"")).to_pylist()), self.escape)
        weight = np.r_[counts, max(1.0, escapes)]
        below, total = self._merged(weight)
        # from the root down: each level's nodes, with their way so far, and the nodes on it down to DEEP
        bits, depth, tail = np.full((n, DEEP), NONE, np.uint8), np.zeros(n, np.int32), np.zeros(n)
        on = np.zeros((n, DEEP), np.int32)
        chance = (total[below[:, 1]] + 0.4) / (total[n:] + 0.8) if n > 1 else np.zeros(0)
        at, way, passed, rest = np.array([2 * n - 2]), np.full((1, DEEP), NONE, np.uint8), np.zeros((1, DEEP), np.int32), np.zeros(1)
        level = 0
        while len(at):
            ends = at < n
            own = at[ends]
            bits[own], on[own], depth[own], tail[own] = way[ends], passed[ends], level, rest[ends]
            inner, way, passed, rest = at[~ends] - n, way[~ends], passed[~ends], rest[~ends]
            at = below[inner].T.ravel() if len(inner) else inner
            way, passed = np.tile(way, (2, 1)), np.tile(passed, (2, 1))
            p = chance[inner]
            if level < DEEP:
                way[: len(inner), level], way[len(inner) :, level] = 0, 1
                passed[:, level] = np.tile(inner, 2)
                rest = np.tile(rest, 2)
            else:
                rest = np.concatenate([rest + np.log10(1 - p), rest + np.log10(p)])
            level += 1
        self.tail = tail
        # three levels of the code are a group, with a block of eight slots: one of each node, and slot 0 for the places
        # past a word's last bit, which belong to no node
        groups = -(-np.minimum(depth, DEEP) // 3)
        self.groups, kept = groups.astype(np.int64), np.arange(DEEP // 3) < groups[:, None]
        self.first = np.cumsum(self.groups) - self.groups
        self.bit = bits.reshape(n, DEEP // 3, 3)[kept]
        odds = np.log(chance / (1 - chance)).astype(np.float32)
        on = on.reshape(n, DEEP // 3, 3)[kept]
        self.logit = np.where(self.bit == NONE, 0, odds.take(on) if n > 1 else 0).astype(np.float32)
        place = np.ones(self.bit.shape, np.uint8)
        place[:, 1] = 2 | self.bit[:, 0] & 1
        place[:, 2] = 4 | (self.bit[:, 0] & 1) << 1 | self.bit[:, 1] & 1
        self.slot = np.where(self.bit == NONE, 0, place).astype(np.uint8)
        with np.errstate(over="ignore"):
            self.hash = on[:, 0].astype(np.uint64) * np.uint64(ODD[1])
        self.set = np.broadcast_to(np.arange(DEEP // 3, dtype=np.uint8) * 4, kept.shape)[kept]

    @staticmethod
    def _merged(weight):
        """The two nodes under each inner node, and the weights of all nodes: leaves first, the root last."""
        import numpy as np

        n = len(weight)
        order = np.argsort(weight, kind="stable")
        light, nodes = weight[order].tolist(), array("i", order.astype(np.int32).tobytes())
        made, left, right = array("d"), array("i"), array("i")
        leaf = at = 0
        for inner in range(n - 1):
            sum_ = 0.0
            for side in (left, right):
                if leaf < n and (at >= inner or light[leaf] <= made[at]):
                    side.append(nodes[leaf])
                    sum_ += light[leaf]
                    leaf += 1
                else:
                    side.append(n + at)
                    sum_ += made[at]
                    at += 1
            made.append(sum_)
        below = np.stack([np.frombuffer(left, np.int32), np.frombuffer(right, np.int32)], 1) if n > 1 else np.zeros((0, 2), np.int32)
        return below, np.concatenate([weight, np.frombuffer(made) if n > 1 else np.zeros(0)])

    def symbols(self, words):
        """Their symbols, of an Arrow array of words."""
        import numpy as np
        import pyarrow.compute as pc

        return pc.index_in(words, value_set=self.words).fill_null(self.escape).to_numpy(zero_copy_only=False).astype(np.int64)


class Portion:
    """Whole texts as symbols, each with its end; the words that have none, with their places."""

    def __init__(self, code: Code, texts: list[str | None]):
        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc

        flat, lengths = split(texts)
        symbols = code.symbols(flat)
        ends = np.cumsum(lengths)
        self.lengths = lengths + 1
        self.symbols = np.insert(symbols, ends, code.end)
        size = pc.binary_length(flat).to_numpy()
        of = np.repeat(np.arange(len(texts)), lengths)
        self.bytes = np.bincount(of, size, len(texts)).astype(np.int64) + self.lengths
        at = np.flatnonzero(symbols == code.escape)
        spelled, places = flat.take(pa.array(at)).to_pylist(), at + of[at]
        if code.end == code.escape:  # no text has ended in training
            last = ends + np.arange(len(texts))
            order = np.argsort(np.r_[places, last], kind="stable")
            spelled = [(spelled + [b""] * len(last))[k] for k in order]
            places = np.r_[places, last][order]
        self.spelled, self.places = spelled, places


def sizes_for(distinct: int, most_slots: int) -> tuple[int, int, int]:
    """log2 of the slots for words' contexts, for bytes' contexts, and for followers."""
    return tuple(max(LEAST_BITS, min(round(math.log2(max(1, k * distinct))), int(math.log2(most_slots)))) for k in (2, 2, 2))


class Tables:
    """Counts of zeros and ones by slot, of words' and then of bytes' contexts; and followers: a check and a symbol, and their lead."""

    def __init__(self, sizes: tuple[int, int, int], counts=None, follower=None, lead=None):
        import numpy as np

        self.sizes = sizes
        n = (1 << sizes[0]) + (1 << sizes[1])
        self.counts = np.zeros(2 * n, np.uint16) if counts is None else counts
        self.follower = np.zeros(1 << sizes[2], np.uint32) if follower is None else follower
        self.lead = np.zeros(1 << sizes[2], np.uint8) if lead is None else lead

    def add(self, slots, bits) -> None:
        """Another look of each bit; counts that near their end are halved."""
        import numpy as np

        at = slots * 2 + bits
        np.add.at(self.counts, at, np.uint16(1))
        full = at[self.counts[at] > 50_000]
        if len(full):
            full = np.unique(full >> 1) * 2
            self.counts[full] >>= np.uint16(1)
            self.counts[full + 1] >>= np.uint16(1)


class Mixer:
    """Weights by gate; the refining table, as ones and all by gate and place; and how often followers were right, of
    how many, by their lead. `settled` are the weights' means over the last batches."""

    def __init__(self, weights=None, refined=None, right=None):
        import numpy as np

        if weights is None:
            weights = np.full((INPUTS, SETS), 0.3, np.float32)
            weights[0, :WORD_SETS] = 0.9
        self.weights, self.settled, self.batches = weights, weights.copy(), 0
        place = np.linspace(-8, 8, APM)
        self.refined = np.stack([np.tile(8 / (1 + np.exp(-place)), SETS), np.full(SETS * APM, 8.0)]) if refined is None else refined
        self.right = np.stack([np.linspace(0.2, 0.9, 256), np.ones(256)]) if right is None else right
        self.right[0, 0] = 0  # there is no follower

    def frozen(self):
        """For scoring: settled weights, and tables of probabilities."""
        import numpy as np

        out = Mixer(self.settled, self.refined, self.right)
        out.table, out.follows = (self.refined[0] / self.refined[1]).astype(np.float32), self.right[0] / self.right[1]
        return out

    def state(self) -> bytes:
        """What partitions add up, but for the weights, which come first."""
        made = Mixer()
        return self.settled.tobytes() + (self.refined - made.refined).tobytes() + (self.right - made.right).tobytes()

    def add(self, state: bytes, share: float) -> None:
        """Another partition's state, which has this share of all bits. The first takes the place of the start's weights."""
        import numpy as np

        cut, end = 4 * self.settled.size, 4 * self.settled.size + 8 * self.refined.size
        self.settled = (0 if not self.batches else self.settled) + np.float32(share) * np.frombuffer(state[:cut], np.float32).reshape(self.settled.shape)
        self.refined += np.frombuffer(state[cut:end]).reshape(self.refined.shape)
        self.right += np.frombuffer(state[end:]).reshape(self.right.shape)
        self.batches = 1

    def mixed(self, x, gate):
        import numpy as np

        dot = self.weights[0].take(gate)
        dot *= x[0]
        for k in range(1, len(x)):
            w = self.weights[k].take(gate)
            w *= x[k]
            dot += w
        return np.clip(dot, -8, 8, out=dot)

    def cells(self, dot, gate):
        """The refining table's place under each bit, and how far the bit is to the next."""
        import numpy as np

        place = (dot + 8) * np.float32((APM - 1.001) / 16)
        low = place.astype(np.intp)
        return gate * np.intp(APM) + low, place - low

    def probability(self, x, gate):
        """That the bit is one, by a frozen mixer."""
        import numpy as np

        dot = self.mixed(x, gate)
        cell, part = self.cells(dot, gate)
        left = self.table.take(cell)
        p = 1 / (1 + np.exp(-dot))
        p += left
        p += (self.table.take(cell + 1) - left) * part
        p *= np.float32(0.5)
        return np.clip(p, 1e-5, 1 - 1e-5, out=p)

    def learn(self, x, gate, bits, rate: float = 0.02) -> None:
        import numpy as np

        for a in range(0, len(bits), BATCH):
            own = [row[a : a + BATCH] for row in x]
            g, b = gate[a : a + BATCH], bits[a : a + BATCH]
            dot = self.mixed(own, g)
            error = b - 1 / (1 + np.exp(-dot))
            step = np.float32(rate) / np.sqrt(1 + np.bincount(g, minlength=SETS))
            for k in range(len(own)):
                self.weights[k] += (step * np.bincount(g, error * own[k], SETS)).astype(np.float32)
            self.batches += 1
            self.settled += (self.weights - self.settled) * np.float32(max(1 / 200, 1 / self.batches))
            cell, part = self.cells(dot, g)
            cell += part > 0.5
            self.refined += np.stack([np.bincount(cell, b, SETS * APM), np.bincount(cell, minlength=SETS * APM)])

    def learn_follows(self, lead, hit) -> None:
        import numpy as np

        self.right += np.stack([np.bincount(lead, hit, 256), np.where(np.arange(256) > 0, np.bincount(lead, minlength=256), 0)])


class Stretch:
    """Some texts' tokens as bits, with what each predictor says of them. `symbols` are theirs in the code; `rare` are the
    places of those that are spelled; `contexts` hash the word before, and the two words before."""

    def __init__(self, code: Code, tables: Tables, symbols, rare, spelled: list[bytes], contexts, logs):
        import numpy as np

        self.code, self.tables, self.symbols, self.contexts, self.logs = code, tables, symbols, contexts, logs
        self._follow()
        self.owner = np.repeat(self.rest, code.groups.take(symbols.take(self.rest)))
        self._words()
        self._bytes(rare, spelled)

    def _follow(self):
        import numpy as np

        both, tables = self.contexts[1], self.tables
        self.follow_slot = (both >> np.uint64(64 - tables.sizes[2])).view(np.int64)
        self.new = ((both >> np.uint64(8)).astype(np.uint32) << np.uint32(20)) | self.symbols.astype(np.uint32)
        self.entry, lead = tables.follower.take(self.follow_slot), tables.lead.take(self.follow_slot)
        differ = self.entry ^ self.new
        self.lead = np.where(differ >> np.uint32(20) == 0, lead, 0)
        self.hit = (differ == 0) & (lead > 0)
        self.rest = np.flatnonzero(~self.hit)

    def _seen(self, slots):
        """A predictor's logit for each slot, and how much it has seen, in four levels."""
        import numpy as np

        counts = self.tables.counts
        if counts.dtype == np.uint8:
            both = counts.view(np.uint16).take(slots)
            return self.logs[1].take(both), self.logs[2].take(both)
        both = counts.view(np.uint32).take(slots)
        zero, one = both & np.uint32(65535), both >> np.uint32(16)
        logit = self.logs[0].take(one)
        logit -= self.logs[0].take(zero)
        n = zero + one
        return logit, (n > 0).view(np.uint8) + (n > 3).view(np.uint8) + (n > 24).view(np.uint8)

    def _words(self):
        import numpy as np

        code, own = self.code, self.symbols.take(self.rest)
        groups = code.groups.take(own)
        ends = np.cumsum(groups)
        at = np.arange(len(self.owner)) + np.repeat(code.first.take(own) - (ends - groups), groups)
        place, hashes = code.slot.take(at, 0), code.hash.take(at)
        self.bits, self.often = code.bit.take(at, 0).ravel(), code.logit.take(at, 0).ravel()
        block = (self.contexts[0].take(self.owner) + hashes) * np.uint64(ODD[2]) >> np.uint64(67 - self.tables.sizes[0])
        self.slots = ((block.view(np.int64) << 3)[:, None] | place).ravel()
        self.set = code.set.take(at)

    def _bytes(self, rare, spelled: list[bytes]):
        import numpy as np

        flat = np.frombuffer(b" ".join(spelled) + b" " if spelled else b"", np.uint8)
        n, size = len(flat), self.tables.sizes[1]
        lengths = np.fromiter(map(len, spelled), np.int64, len(spelled)) + 1
        start = np.repeat(np.cumsum(lengths) - lengths, lengths)
        into, wide = np.arange(n) - start, flat.astype(np.uint64)
        with np.errstate(over="ignore"):
            one, two = np.r_[np.uint64(0), wide[:-1]], np.r_[np.zeros(2, np.uint64), wide[:-2]][:n]
            one[into < 1], two[into < 2] = 0, 0
            contexts = [(one | two << np.uint64(8)) * np.uint64(ODD[0])]
            # sums of bytes by powers of an odd number give every beginning of a word a hash; the inverse takes the place out
            odd = ODD[3]
            powers = np.cumprod(np.r_[np.uint64(1), np.full(n, odd, np.uint64)])
            inverse = np.cumprod(np.r_[np.uint64(1), np.full(n, pow(odd, -1, 1 << 64), np.uint64)])
            sums = np.r_[np.uint64(0), np.cumsum((wide + np.uint64(1)) * powers[:n])]
            h = ((sums[np.arange(n)] - sums[start]) * inverse[start] ^ np.uint64(5)) * np.uint64(ODD[1])
            contexts.append(h ^ h >> np.uint64(32))
            high = flat >> 4
            half = np.stack([np.zeros(n, np.uint64), (high.astype(np.uint64) + np.uint64(1)) * np.uint64(ODD[1])], 1)
            nibble = np.stack([high, flat & 15], 1)
            shifts = np.arange(3, -1, -1, dtype=np.uint8)
            bits = (nibble[:, :, None] >> shifts) & 1
            node = (np.uint8(16) | nibble)[:, :, None] >> np.arange(4, 0, -1, dtype=np.uint8)
            slots = []
            for c in contexts:
                block = (((c[:, None] + half) * np.uint64(ODD[2])) >> np.uint64(68 - size)).astype(np.int64) << 4
                slot = ((1 << self.tables.sizes[0]) + (block[:, :, None] | node)).ravel()
                slots.append(slot)
        self.byte_bits, self.byte_slots, self.byte_owner = bits.ravel(), slots, np.repeat(rare, lengths)

    def predicted(self):
        """The mixer's inputs and gate, for words' bits and for bytes' bits."""
        import numpy as np

        before, level = self._seen(self.slots)
        (two, some), (all_, most) = map(self._seen, self.byte_slots)
        return ([self.often, before], np.repeat(self.set, 3) | level), ([two, all_], np.uint8(WORD_SETS) + (some << np.uint8(2) | most))

    def scores(self, mixer: Mixer):
        """log10 of each token's probability."""
        import numpy as np

        follows = mixer.follows.take(self.lead)
        out = np.log10(np.where(self.hit, follows, 1 - follows))
        out[self.rest] += self.code.tail.take(self.symbols.take(self.rest))
        for (x, gate), bits, owner, each in zip(self.predicted(), (self.bits, self.byte_bits), (self.owner, self.byte_owner), (3, 8), strict=True):
            p = mixer.probability(x, gate)
            np.subtract(1, p, out=p, where=bits == 0)
            p[bits == NONE] = 1
            out += np.bincount(owner, np.log10(p.reshape(-1, each).prod(1, dtype=np.float64)), len(out))
        return out

    def learn(self, mixer: Mixer | None) -> int:
        """Adds to the tables and, if one is given, lets the mixer learn from what it would have said before."""
        import numpy as np

        real = np.flatnonzero(self.bits != NONE)
        bits = self.bits.take(real)
        if mixer:
            (x, gate), (byte_x, byte_gate) = self.predicted()
            mixer.learn([v.take(real) for v in x], gate.take(real), bits)
            mixer.learn(byte_x, byte_gate, self.byte_bits)
            mixer.learn_follows(self.lead, self.hit)
        t = self.tables
        t.add(self.slots.take(real), bits)
        for slots in self.byte_slots:
            t.add(slots, self.byte_bits)
        lead = t.lead.take(self.follow_slot)
        same, weak = self.entry == self.new, lead <= 1
        t.follower[self.follow_slot] = np.where(same | ~weak, self.entry, self.new)
        t.lead[self.follow_slot] = np.where(same, np.minimum(lead, 254) + 1, np.where(weak, 1, lead - 1))
        return len(self.symbols)


def log_table():
    """Logarithms of counts; and logits and levels of two counts of one byte each, as one number."""
    import numpy as np

    log = np.log(np.arange(1 << 16, dtype=np.float32) + np.float32(0.4))
    zero, one = np.arange(1 << 16) & 255, np.arange(1 << 16) >> 8
    n = zero + one
    return log, log[one] - log[zero], ((n > 0).astype(np.uint8) + (n > 3) + (n > 24)).astype(np.uint8)


def stretches(code: Code, tables: Tables, texts: list[str | None], logs, portion: Portion | None = None) -> Iterator[Stretch]:
    """The tokens of the texts, a bounded number at a time; contexts reach back to the start of a text."""
    import numpy as np

    p = Portion(code, texts) if portion is None else portion
    starts = np.cumsum(p.lengths) - p.lengths
    named = np.zeros(len(p.spelled), np.uint64)
    named[:] = [zlib.crc32(w) for w in p.spelled]
    for a in range(0, len(p.symbols), STRETCH):
        b = min(len(p.symbols), a + STRETCH)
        # two tokens more, for the contexts of the first
        low = max(0, a - 2)
        i, j, k = np.searchsorted(p.places, (low, a, b))
        names = (p.symbols[low:b] + 1).astype(np.uint64)
        names[p.places[i:k] - low] = named[i:k] + np.uint64(1 << 33)
        first = np.zeros(b - low, bool)
        x, y = np.searchsorted(starts, (low, b))
        first[starts[x:y] - low] = True
        with np.errstate(over="ignore"):
            last = np.r_[np.uint64(0), names[:-1]]
            last[first] = 0
            older = np.r_[np.uint64(0), last[:-1]]
            older[first] = 0
            one = (last + np.uint64(1)) * np.uint64(ODD[0])
            both = (one ^ (older + np.uint64(3)) * np.uint64(ODD[1])) * np.uint64(ODD[2])
            contexts = (one ^ one >> np.uint64(31), both ^ both >> np.uint64(32))
        yield Stretch(code, tables, p.symbols[a:b], p.places[j:k] - a, p.spelled[j:k], [c[a - low :] for c in contexts], logs)


def _word_counts(docs: DataFrame, id_column: str, text_column: str) -> DataFrame:
    """(word, c): all words, the empty one standing for the end, with their counts in training texts."""

    def kernel(batches: Iterator[dict]) -> Iterator[dict]:
        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc

        held, rows = [], 0

        def summed():
            return pa.concat_tables(held).group_by("word").aggregate([("c", "sum")]).rename_columns(["word", "c"])

        def emitted(table):
            for part in table.combine_chunks().to_batches(max_chunksize=20_000):
                yield {"word": part.column("word").cast(pa.binary()), "c": part.column("c")}

        for b, some in ((b, some) for b in batches for some in ranges(b[text_column])):
            flat, lengths = split(b[text_column][some])
            trains = ~np.array(b["held_out"][some], bool)
            counts = pc.value_counts(flat.filter(pa.array(np.repeat(trains, lengths))))
            other = pc.unique(flat.filter(pa.array(np.repeat(~trains, lengths))))
            words = [counts.field("values"), other, pa.array([b""], pa.large_binary())]
            n = [counts.field("counts").cast(pa.int64()), pa.array(np.zeros(len(other), np.int64)), pa.array([int(trains.sum())])]
            held.append(pa.table({"word": pa.chunked_array(words), "c": pa.chunked_array(n)}))
            rows += len(held[-1])
            if rows > MOST_HELD:
                held = [summed()]
                rows = len(held[0])
                if rows > MOST_HELD // 2:
                    yield from emitted(held[0])
                    held, rows = [], 0
        if held:
            yield from emitted(summed())
        held = []
        give_back()

    found = map_texts(docs, [text_column, "held_out"], kernel, "word binary, c long")
    return found.groupBy("word").agg(F.sum("c").alias("c"))


def _parts(tables: Tables) -> Iterator[tuple[int, bytes]]:
    """Blocks of counts by number, then, by numbers under zero, blocks of followers with their leads; empty ones are left out."""
    for k in range(0, len(tables.counts), 2 * BLOCK):
        own = tables.counts[k : k + 2 * BLOCK]
        if own.any():
            yield k // (2 * BLOCK), own.tobytes()
    for k in range(0, len(tables.follower), BLOCK):
        lead = tables.lead[k : k + BLOCK]
        if lead.any():
            yield -1 - k // BLOCK, tables.follower[k : k + BLOCK].tobytes() + lead.tobytes()


def _joined(block: int, parts: list[bytes]) -> bytes:
    """Counts of some tasks added, and halved until they fit; followers by the largest lead, less the next one's."""
    import numpy as np

    if block >= 0:
        total = sum(np.frombuffer(x, np.uint16).astype(np.uint32) for x in parts).reshape(-1, 2)
        while (over := total.max(1) > 65_535).any():
            total[over] >>= 1
        return total.astype(np.uint16).tobytes()
    n = len(parts[0]) // 5
    follower, lead = np.frombuffer(parts[0][: 4 * n], np.uint32).copy(), np.frombuffer(parts[0][4 * n :], np.uint8).astype(np.int64)
    for x in parts[1:]:
        f, m = np.frombuffer(x[: 4 * n], np.uint32), np.frombuffer(x[4 * n :], np.uint8).astype(np.int64)
        same = f == follower
        lead = np.where(same, lead + m, lead - m)
        turned = lead < 0
        follower[turned] = f[turned]
        lead = np.abs(lead)
    return follower.tobytes() + np.minimum(lead, 255).astype(np.uint8).tobytes()


def _learned(training: DataFrame, text_column: str, code, sizes: tuple[int, int, int], run: str):
    """(Tables with counts of one byte, Mixer): what the partitions learn from all of their texts, put together."""
    import numpy as np

    spark = training.sparkSession
    cores = spark.sparkContext.defaultParallelism
    groups = max(1, math.isqrt(cores))

    def kernel(batches: Iterator[dict]) -> Iterator[dict]:
        tables, mixer, logs, n, part = Tables(sizes), Mixer(), log_table(), 0, 0
        own = worker_code(code, run)
        for b in batches:
            part = b["part"][0] if b["part"] else part
            for some in ranges(b[text_column]):
                for s in stretches(own, tables, b[text_column][some], logs):
                    n += s.learn(mixer)
        if n:
            for block, content in _parts(tables):
                yield {"block": [block], "part": [part], "n": [n], "content": [content]}
            yield {"block": [MIXERS], "part": [part], "n": [n], "content": [mixer.state()]}
        del tables
        give_back()

    schema = "block int, part int, n long, content binary"
    # a table of counts for each core, not for each split
    parts = map_texts(training.coalesce(cores).withColumn("part", F.spark_partition_id()), [text_column, "part"], kernel, schema)

    def add(last: bool):
        def joined(group):
            import pandas as pd

            group = group.sort_values("part")
            block = int(group.block.iloc[0])
            if block == MIXERS:
                return group[["block", "part", "n", "content"]]
            content = _joined(block, list(group.content))
            if last and block >= 0:
                pair = np.frombuffer(content, np.uint16).reshape(-1, 2).astype(np.uint32)
                most = np.maximum(pair.max(1), 255)[:, None]
                content = np.where(pair > 0, np.maximum(pair * 255 // most, 1), 0).astype(np.uint8).tobytes()
            return pd.DataFrame({"block": [block], "part": [int(group.part.iloc[0]) % groups], "n": [0], "content": [content]})

        return joined

    if cores > 64:
        parts = parts.withColumn("g", F.pmod("part", F.lit(groups))).groupBy("block", "g").applyInPandas(add(False), schema)
    parts = parts.groupBy("block").applyInPandas(add(True), schema)
    whole = Tables(sizes, counts=np.zeros(2 * ((1 << sizes[0]) + (1 << sizes[1])), np.uint8))
    states = []
    for row in parts.toLocalIterator():
        if row.block == MIXERS:
            states.append(row)
        elif row.block >= 0:
            own = np.frombuffer(row.content, np.uint8)
            whole.counts[2 * BLOCK * row.block : 2 * BLOCK * row.block + len(own)] = own
        else:
            at, n = BLOCK * (-1 - row.block), len(row.content) // 5
            whole.follower[at : at + n] = np.frombuffer(row.content[: 4 * n], np.uint32)
            whole.lead[at : at + n] = np.frombuffer(row.content[4 * n :], np.uint8)
    mixer, total = Mixer(), sum(r.n for r in states)
    for r in sorted(states, key=lambda r: r.part):
        mixer.add(r.content, r.n / total)
    release(spark)
    return whole, mixer


def worker_code(code, run: str) -> Code:
    return worker_cache(f"context mixing {run}", "code", lambda: Code(*code.value))


def score_texts(docs: DataFrame, folds: int = 7, held_fold: int = 2, frequent: int = 400_000, most_slots: int = 1 << 25, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """One row per document: id, held_out, n_tokens, n_known, train_tokens, base_score, score and
    bits_per_byte. `base_score` is the unigram model with one added to each count.

    `frequent`, under 2^20, is the number of words with a code; others are spelled, and their counts for `base_score`
    are joined. `most_slots` bounds each table of contexts by what a worker holds: 4 bytes a slot while it learns.
    """
    spark = docs.sparkSession
    kind = docs.schema[id_column].dataType.simpleString()
    fold = F.pmod(F.crc32(F.coalesce(F.col(id_column).cast("string"), F.lit("")).cast("binary")), F.lit(folds))
    docs = docs.select(id_column, text_column, (fold == held_fold).alias("held_out"))
    words = materialize(_word_counts(docs, id_column, text_column))
    totals = words.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.when(F.col("c") > 0, 1))).first()
    n_train, n_distinct = totals[0], totals[1]

    # words seen once stay out of the code: they stand for those that were never seen
    top = words.filter((F.length("word") <= 64) & (F.col("c") > 1)).orderBy(F.desc("c"), "word").limit(frequent).select("word", "c").toArrow()
    names, counted = top.column("word").combine_chunks(), top.column("c").to_numpy()
    code = spark.sparkContext.broadcast((names, counted, n_train - int(counted.sum()) + 1))
    run = uuid.uuid4().hex
    sizes = sizes_for(n_distinct, most_slots)
    learned, mixer = _learned(docs.filter(~F.col("held_out")), text_column, code, sizes, run)
    model = spark.sparkContext.broadcast((learned.counts, learned.follower, learned.lead, mixer.settled, mixer.refined, mixer.right))
    del learned
    less = math.log10(n_train + n_distinct + 1)

    def look_up(batches: Iterator[dict]) -> Iterator[dict]:
        import numpy as np
        import pyarrow as pa
        from pyspark import TaskContext

        own = worker_code(code, run)

        def made():
            counts, follower, lead, *mixed = model.value
            c = np.r_[code.value[1].astype(np.float64), 0]
            base = np.log10(c + 1) - less
            base[-1] = 0  # the escape's words are joined
            return Tables(sizes, counts, follower, lead), Mixer(*mixed).frozen(), base, log_table()

        tables, mixer, base, logs = worker_cache(f"context mixing {run}", "model", made)
        row = TaskContext.get().partitionId() << 40
        for b, some in ((b, some) for b in batches for some in ranges(b[text_column])):
            p = Portion(own, b[text_column][some])
            n, of = len(p.lengths), np.repeat(np.arange(len(p.lengths)), p.lengths)
            lm = np.concatenate([np.zeros(0), *(s.scores(mixer) for s in stretches(own, tables, [], logs, p))])
            ends = np.r_[0, np.cumsum(np.bincount(of[p.places], minlength=n))]
            yield {
                "row": np.arange(row, row + n), id_column: b[id_column][some], "held_out": b["held_out"][some], "n_tokens": p.lengths, "n_known": p.lengths - np.diff(ends),
                "words": pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(p.spelled, pa.binary())),
                "base": np.bincount(of, base[p.symbols], n), "lm": np.bincount(of, lm, n), "bytes": p.bytes,
            }
            row += n

    rows = map_texts(docs, [id_column, text_column, "held_out"], look_up, f"row long, {id_column} {kind}, held_out boolean, words array<binary>, n_tokens long, n_known long, base double, lm double, bytes long")
    # the words that are not in the code meet their counts; a word of its own, which no text can hold, keeps each document's numbers
    per_text = ["n_tokens", "n_known", "base", "lm", "bytes", "held_out", id_column]
    mark = F.array(F.concat(F.lit(" "), F.col("row").cast("string")).cast("binary"))
    spread = rows.select("row", *per_text, F.posexplode(F.concat(mark, "words")).alias("at", "word"))
    spread = spread.select("row", "word", (F.col("at") > 0).alias("rare"), *(F.when(F.col("at") == 0, F.col(c)).alias(c) for c in per_text))
    joined = spread.join(words, "word", "left")
    sums = joined.groupBy("row").agg(
        F.first(id_column, ignorenulls=True).alias(id_column), F.first("held_out", ignorenulls=True).alias("held_out"), F.sum("n_tokens").alias("n_tokens"),
        (F.sum("n_known") + F.count_if(F.col("c") > 0)).alias("n_known"),
        (F.sum("base") + F.sum(F.when(F.col("rare"), F.log10(F.coalesce("c", F.lit(0)) + 1) - less).otherwise(0.0))).alias("base_score"),
        F.sum("lm").alias("score"), F.sum("bytes").alias("bytes"),
    )
    bits = (-F.col("score") / math.log10(2) / F.col("bytes")).alias("bits_per_byte")
    return sums.select(id_column, "held_out", "n_tokens", "n_known", F.lit(n_train).cast("long").alias("train_tokens"), "base_score", "score", bits)
