"""Near-duplicates: universal hash minima in bands, checked signatures and sets, connected components.

1. Each document becomes its set of word shingles, as 64-bit hashes. Documents of equal
   sets form a class, named by a hash of the set; copies cost one row each, and go no further.
2. A class has `bands * rows` minima of universal hashes; each band of them is a bucket key.
3. Every member of a bucket is compared with its leader, the bucket's smallest class: first
   by signature, then, where that leaves a doubt, on the full sets.
4. The links' components are found by large-star and small-star rounds.
5. Buckets that still hold several components are compared once more, members outside
   the bucket's largest component against all other members, in blocks of bounded bytes, so
   no link between them is lost and groups that are already one component cost nothing.
   Buckets that share their largest component, and so most sets, are compared as one.

A pair of exactly the wanted similarity shares no bucket with a probability of
(1 - s^rows)^bands: 6e-6 for 0.8, 6 rows and 40 bands, and less for closer pairs.

Defined results: a null or blank text has an empty set and is linked with nothing;
texts are taken whole; a text of fewer words than a shingle is one shingle; repeated
rows each come out, with equal results, and a row whose id also has another text is
judged by its own text; a null id takes part in no bucket, but shares the component of
equal sets; ids are integers; an empty table gives an empty result; further columns are
ignored or, by `deduplicate`, kept.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from strata.llm.common import map_texts, materialize, release, worker_cache
from strata.llm.components import connected_components

LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
#: Bytes of sets and signatures on either side of two blocks when the members of a bucket are compared.
BLOCK_BYTES = 4_000_000
#: Times the comparisons of separate buckets up to which buckets of one component are compared as one group.
MERGE = 4
#: Signature estimates this far under the wanted similarity leave no doubt: over five standard errors of 240 minima.
DOUBT = 0.14
#: Words whose hash a worker remembers before it starts anew.
MOST_KNOWN = 400_000


class _WordHash(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= MOST_KNOWN:
            self.clear()
        h = self[word] = int.from_bytes(hashlib.blake2b(word, digest_size=8).digest(), "little")
        return h


def shingle_set(text: str | None, width: int):
    """Sorted distinct 64-bit hashes of the shingles."""
    import numpy as np

    words = (text or "").encode("utf-8", "surrogatepass").translate(LOWER).split()
    if not words:
        return np.empty(0, np.uint64)
    known = worker_cache("near-duplicates", "word hashes", _WordHash)
    h = np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
    take = min(width, len(h))
    with np.errstate(over="ignore"):
        s = np.full(len(h) - take + 1, take, np.uint64)
        for k in range(take):
            s = (s ^ h[k : k + len(s)]) * np.uint64(0x9E3779B97F4A7C15)
            s ^= s >> np.uint64(29)
        s = (s ^ (s >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
        s ^= s >> np.uint64(32)
    return np.unique(s)


def _minima(sets: list, n: int):
    """The `n` hash minima of each set, by multiply-and-add hashes on 32 bits; odd factors make them permutations."""
    import numpy as np

    draw = np.random.default_rng(20_011)
    factors = draw.integers(0, 2**31, n, dtype=np.uint64).astype(np.uint32) * np.uint32(2) + np.uint32(1)
    shifts = draw.integers(0, 2**32, n, dtype=np.uint64).astype(np.uint32)
    out = np.full((len(sets), n), 0xFFFFFFFF, np.uint32)
    filled = [k for k, s in enumerate(sets) if len(s)]
    at = 0
    while at < len(filled):
        upto, size = at, 0
        while upto < len(filled) and (upto == at or size + len(sets[filled[upto]]) <= 60_000):
            size += len(sets[filled[upto]])
            upto += 1
        own = filled[at:upto]
        x = np.concatenate([sets[k] for k in own])
        x = (x ^ (x >> np.uint64(32))).astype(np.uint32)
        starts = np.cumsum([0] + [len(sets[k]) for k in own[:-1]])
        part = np.empty((n, len(own)), np.uint32)
        for j in range(n):
            part[j] = np.minimum.reduceat(x * factors[j] + shifts[j], starts)
        out[own] = part.T
        at = upto
    return out


def _described(docs: DataFrame, width: int, bands: int, rows: int, id_column: str, text_column: str) -> DataFrame:
    """(id, n_shingles, same, keys, sig): the set's size and digest, its band keys, and a byte of each minimum."""

    def kernel(batches: Iterator[dict]) -> Iterator[dict]:
        import numpy as np
        import pyarrow as pa

        mixers = np.random.default_rng(5).integers(1, 2**63, rows, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        for b in batches:
            sets = [shingle_set(t, width) for t in b[text_column]]
            minima = _minima(sets, bands * rows)
            with np.errstate(over="ignore"):
                keys = (minima.astype(np.uint64).reshape(len(sets), bands, rows) * mixers).sum(axis=2, dtype=np.uint64)
                keys ^= keys >> np.uint64(31)
            sig = (minima >> np.uint32(11)).astype(np.uint8)
            yield {
                "id": b[id_column],
                "n_shingles": [len(s) for s in sets],
                "same": [set_digest(s) for s in sets],
                "keys": pa.FixedSizeListArray.from_arrays(pa.array(keys.view(np.int64).ravel()), bands).cast(pa.list_(pa.int64())),
                "sig": [s.tobytes() if len(x) else None for s, x in zip(sig, sets, strict=True)],
            }

    return map_texts(docs, [id_column, text_column], kernel, "id long, n_shingles long, same binary, keys array<long>, sig binary")


def _checked(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets have at least `percent` per cent of their union in common."""

    def kernel(batches: Iterator[dict]) -> Iterator[dict]:
        import numpy as np

        for batch in batches:
            kept = []
            for a, b, x, y in zip(batch["a"], batch["b"], batch["x"], batch["y"], strict=True):
                x, y = np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)
                both = len(np.intersect1d(x, y, assume_unique=True))
                if both and 100 * both >= percent * (len(x) + len(y) - both):
                    kept.append((a, b))
            yield {"a": [a for a, _ in kept], "b": [b for _, b in kept]}

    joined = pairs.join(sets.select(F.col("c").alias("b"), F.col("set").alias("y")), "b").join(sets.select(F.col("c").alias("a"), F.col("set").alias("x")), "a")
    return map_texts(joined, ["a", "b", "x", "y"], kernel, "a long, b long")


def class_number(digest: bytes) -> int:
    """The name of a class: the first half of its set's digest."""
    return int.from_bytes(digest[:8], "big", signed=True)


def set_digest(shingles) -> bytes | None:
    return hashlib.blake2b(shingles.tobytes(), digest_size=16).digest() if len(shingles) else None


def _id_filter(ids: DataFrame, bits: int = 1 << 24):
    """A bitmap of hashed ids, of a fixed size whatever the number of ids: no id is missed, some others pass."""
    x = F.pmod(F.xxhash64("id"), F.lit(bits))
    parts = ids.select((x + 1).alias("x")).groupBy(F.bitmap_bucket_number("x").alias("k")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("x")).alias("m")).collect()
    bitmap = bytearray(bits // 8)
    for r in parts:
        bitmap[(r.k - 1) * 4096 : r.k * 4096] = r.m
    return x, ids.sparkSession.sparkContext.broadcast(bytes(bitmap))


def _sets(docs: DataFrame, wanted: DataFrame, width: int, id_column: str, text_column: str) -> DataFrame:
    """(c, set) of the classes in `wanted` (c, id), each from the document named there. Texts do not move: the scan
    passes over other documents by a bitmap."""
    x, bitmap = _id_filter(wanted)

    def kernel(batches: Iterator[dict]) -> Iterator[dict]:
        held = bitmap.value
        for b in batches:
            own = [k for k, x in enumerate(b["x"]) if x is not None and held[x >> 3] >> (x & 7) & 1]
            sets = [(b["id"][k], shingle_set(b["text"][k], width)) for k in own]
            sets = [(i, s) for i, s in sets if len(s)]
            yield {"id": [i for i, _ in sets], "c": [class_number(set_digest(s)) for _, s in sets], "set": [s.tobytes() for _, s in sets]}

    named = docs.select(F.col(id_column).cast("long").alias("id"), F.col(text_column).alias("text")).withColumn("x", x)
    found = map_texts(named, ["id", "text", "x"], kernel, "id long, c long, set binary")
    return found.join(wanted, ["c", "id"], "left_semi").dropDuplicates(["c", "id"]).select("c", "set")


def _met(left: DataFrame) -> DataFrame:
    """(k, c, component, asks): who is compared with whom. Buckets with the same largest component are one group
    where that takes at most MERGE times their own comparisons, so that sets they share move once; others stay alone."""
    alone = left.groupBy("top", "k").agg(F.count("*").alias("n"), F.count_if("asks").alias("o")).groupBy("top").agg(F.sum(F.col("n") * F.col("o")).alias("apart"))
    members = materialize(left.groupBy("top", "c", "component").agg(F.bool_or("asks").alias("asks")))
    whole = members.groupBy("top").agg((F.count("*") * F.count_if("asks")).alias("together"))
    tops = materialize(alone.join(whole, "top").select("top", (F.col("together") <= MERGE * F.col("apart")).alias("merge")))
    one = members.join(tops.filter("merge"), "top").select(F.xxhash64("top", F.lit("top")).alias("k"), "c", "component", "asks")
    return one.union(left.join(tops.filter("not merge"), "top").select("k", "c", "component", "asks"))


def _across(members: DataFrame, content: DataFrame, percent: int, least: float) -> DataFrame:
    """Links (a, b) between members (k, c, component, asks) of equal k and unequal components, of which a asks.
    Those that ask and all members are cut into blocks of bounded bytes that meet pairwise; a block pair gives one
    link at most for each asking class and other component."""

    def blocks(weight):
        return F.greatest(F.ceil(F.sum(weight) / BLOCK_BYTES), F.lit(1)).cast("int")

    weighed = members.join(content.select("c", (F.octet_length("set") + F.octet_length("sig")).alias("w")), "c")
    sizes = weighed.groupBy("k").agg(blocks(F.when(F.col("asks"), F.col("w")).otherwise(0)).alias("n_o"), blocks(F.col("w")).alias("n_t"))
    h, upto = F.xxhash64("c"), lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    sized = members.join(sizes, "k")
    one = sized.filter("asks").select("k", "c", "component", F.lit(True).alias("asks"), F.pmod(h, "n_o").cast("int").alias("o"), upto("n_t").alias("t"))
    two = sized.select("k", "c", "component", F.lit(False).alias("asks"), upto("n_o").alias("o"), F.pmod(h, "n_t").cast("int").alias("t"))

    def compare(group):
        import numpy as np
        import pandas as pd

        own, others = group[group.asks], group[~group.asks]
        got = []
        if len(own) and len(others):
            y = np.frombuffer(b"".join(others.sig), np.uint8).reshape(len(others), -1)
            names, parts, theirs = others.c.to_numpy(), others.component.to_numpy(), [np.frombuffer(x, np.uint64) for x in others.set]
            for i, c, sig, mine in zip(own.c, own.component, own.sig, own.set, strict=True):
                share = ((y == np.frombuffer(sig, np.uint8)).mean(axis=1) - 1 / 256) / (255 / 256)
                near = np.flatnonzero((share >= least) & (parts != c))
                mine, joined = np.frombuffer(mine, np.uint64), set()
                for j in near[np.argsort(-share[near], kind="stable")]:
                    if parts[j] not in joined:
                        both = len(np.intersect1d(mine, theirs[j], assume_unique=True))
                        if 100 * both >= percent * (len(mine) + len(theirs[j]) - both):
                            got.append((i, names[j]))
                            joined.add(parts[j])
        return pd.DataFrame(got, columns=["a", "b"], dtype="int64")

    return one.unionByName(two).join(content, "c").groupBy("k", "o", "t").applyInPandas(compare, "a long, b long")


def near_duplicates(docs: DataFrame, width: int = 5, percent: int = 80, bands: int = 40, rows: int = 6, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """One row per document: its id, n_shingles, component_id and kept (it is the smallest of its component)."""
    return _judged(docs, width, percent, bands, rows, id_column, text_column).select(F.col("id").alias(id_column), "n_shingles", "component_id", F.col("id").eqNullSafe(F.col("component_id")).alias("kept"))


def _judged(docs: DataFrame, width: int, percent: int, bands: int, rows: int, id_column: str, text_column: str) -> DataFrame:
    """(id, n_shingles, c, component_id) of every row; c, the class, is null for blank texts."""
    least = percent / 100 - DOUBT
    all_rows = materialize(_described(docs.withColumn(id_column, F.col(id_column).cast("long")), width, bands, rows, id_column, text_column))
    number = F.conv(F.substring(F.hex("same"), 1, 16), 16, -10).cast("long")
    classes = materialize(all_rows.filter("same is not null and id is not null").groupBy("same").agg(F.min("id").alias("id"), F.first("keys").alias("keys"), F.first("sig").alias("sig")).withColumn("c", number))

    members = classes.select("c", F.posexplode("keys").alias("band", "key"))
    buckets = members.groupBy("band", "key").agg(F.min("c").alias("a"), F.count("*").alias("n")).filter("n > 1")
    placed = materialize(members.join(buckets, ["band", "key"]).select("band", "key", "n", "a", "c"))
    sets = materialize(_sets(docs, classes.select("c", "id").join(placed.select("c").distinct(), "c", "left_semi"), width, id_column, text_column))
    release(docs.sparkSession)
    signed = classes.select("c", "sig")

    def doubtful(batches: Iterator[dict]) -> Iterator[dict]:
        import numpy as np

        for batch in batches:
            if not batch["a"]:
                continue
            x, y = (np.frombuffer(b"".join(batch[c]), np.uint8).reshape(len(batch["a"]), -1) for c in ("x", "y"))
            share = (x == y).mean(axis=1, dtype=np.float32)
            keep = np.flatnonzero((share - 1 / 256) / (255 / 256) >= least)
            yield {c: [batch[c][k] for k in keep] for c in ("a", "b")}

    def linked(pairs: DataFrame) -> DataFrame:
        """Those of the pairs whose signatures, and then whose full sets, agree."""
        both = pairs.join(signed.select(F.col("c").alias("b"), F.col("sig").alias("y")), "b").join(signed.select(F.col("c").alias("a"), F.col("sig").alias("x")), "a")
        return materialize(_checked(map_texts(both, ["a", "b", "x", "y"], doubtful, "a long, b long").distinct(), sets, percent))

    links = linked(placed.filter("a <> c").select("a", F.col("c").alias("b")).distinct())
    release(docs.sparkSession)
    found = materialize(connected_components(links))

    # Buckets with several components left: their members outside the largest component meet all of the bucket's
    # members. Buckets of the same members are one.
    belongs = placed.filter("n > 2").join(found.withColumnRenamed("id", "c"), "c", "left").withColumn("component", F.coalesce("component", "c"))
    belongs = materialize(belongs.select(F.xxhash64("band", "key").alias("k"), "c", "component"))
    parts = belongs.groupBy("k", "component").agg(F.count("*").alias("size"))
    mixed = parts.groupBy("k").agg(F.count("*").alias("parts"), F.max(F.struct("size", "component"))["component"].alias("top")).filter("parts > 1").select("k", "top")
    left = materialize(belongs.join(mixed, "k").select("k", "top", "c", "component", (F.col("component") != F.col("top")).alias("asks")))
    if not left.isEmpty():
        more = materialize(_across(_met(left), sets.join(signed, "c"), percent, least).distinct())
        release(docs.sparkSession)
        found = connected_components(links.union(more))

    named = classes.select("c", "same", "id").join(found.withColumnRenamed("id", "c"), "c", "left").withColumn("component", F.coalesce("component", "c"))
    smallest = named.groupBy("component").agg(F.min("id").alias("component_id"))
    heads = named.select("same", "component").join(smallest, "component").select("same", "component_id")
    out = all_rows.select("id", "n_shingles", "same").join(heads, "same", "left")
    return out.select("id", "n_shingles", number.alias("c"), F.coalesce("component_id", "id").alias("component_id"))


def deduplicate(docs: DataFrame, width: int = 5, percent: int = 80, bands: int = 40, rows: int = 6, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """The documents that stay, with all their columns: one row of each component, and every row of a blank text.

    Rows of an id that is not repeated are told by it, so their texts meet no others. Of repeated ids, the sets are
    found again, and one row stays where several are of the component's smallest id.
    """
    judged = materialize(_judged(docs, width, percent, bands, rows, id_column, text_column))
    same_id = F.col(id_column).cast("long").eqNullSafe(F.col("_id"))
    stays = F.col("id").eqNullSafe(F.col("component_id"))
    gone = judged.filter(~stays).select(F.col("id").alias("_id")).distinct()
    repeated = materialize(judged.groupBy(F.col("id").alias("_id")).agg(F.count("*").alias("n")).filter("n > 1").select("_id"))
    if repeated.isEmpty():
        return docs.join(gone, same_id, "left_anti")
    once = docs.join(gone.union(repeated), same_id, "left_anti")

    names = docs.columns
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)

    def kernel(batches: Iterator[dict]) -> Iterator[dict]:
        for b in batches:
            digests = [set_digest(shingle_set(t, width)) for t in b[text_column]]
            yield b | {"_c": [None if d is None else class_number(d) for d in digests]}

    again = map_texts(docs.join(repeated, same_id, "left_semi"), names, kernel, f"{schema}, _c long")
    blank = again.filter("_c is null").select(names)
    # of the rows of a component's smallest id, one class stays, and of its rows the one of smallest hash
    heads = judged.filter(stays & F.col("c").isNotNull()).groupBy("component_id", F.when(F.col("id").isNull(), F.col("c")).alias("own")).agg(F.min("c").alias("_c"))
    heads = heads.select(F.col("component_id").alias("_id"), F.col("_c").alias("_head"))
    whole = again.join(heads, same_id & (F.col("_c") == F.col("_head"))).groupBy("_id", "_head").agg(F.min_by(F.struct(*names), F.xxhash64(*names)).alias("row"))
    return once.union(blank).union(whole.select("row.*"))
