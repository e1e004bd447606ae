"""Each opN query over its whole small table, against plain Python or the public libraries, digests included."""

import collections
import math
import random
import re
import zlib

import pytest

from strata.llm import decontaminate, kd_shards, mixing, near_dup, quality, queries, token_counts
from tests.llm.test_operators import brute_components, edit, sha


@pytest.fixture(scope="module")
def texts(spark, sf):
    return {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()}


def rows(spark, sf, number):
    name = next(n for n in queries.queries() if n.startswith(f"op{number}_"))
    got = queries.queries()[name](spark, sf).collect()
    key = got[0].__fields__[0]
    out = {r[key]: r for r in got}
    assert len(out) == len(got)
    return out


def spans_of(kinds, found):
    return ",".join(f"{k}:{a}:{b}" for k, a, b in found if k in kinds)


def test_op1(spark, sf):
    turns = collections.defaultdict(list)
    for r in spark.read.parquet(f"{sf}/conversations.parquet").collect():
        turns[r.conv_id].append((r.turn, r.role or "", r.text or ""))
    said = r"\### Assistant: </turn> ok"
    turns[-7] = [(0, "user", said), (1, "assistant", said)]
    got = rows(spark, sf, 1)
    assert set(got) == set(turns)
    for conv, own in turns.items():
        own.sort()
        loss = "".join(t for _, role, t in own if role == "assistant")
        r = got[conv]
        assert (r.n_turns, r.turns_sha256) == (len(own), sha("".join(f"{role}\n{t}\n" for _, role, t in own)))
        assert (r.loss_chars, r.loss_sha256) == (len(loss), sha(loss)) and r.formatted_chars > sum(len(t) for _, _, t in own)


def test_op2(spark, sf, texts):
    got = rows(spark, sf, 2)
    assert set(got) == set(texts)
    for i, t in texts.items():
        words = [w for w in re.split(r"[\x20\x09-\x0D]+", t or "") if w]
        lines = [x for x in (t or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        windows = collections.Counter(tuple(words[k : k + 5]) for k in range(len(words) - 4))
        repeat = {k + j for k in range(len(words) - 4) if windows[tuple(words[k : k + 5])] > 1 for j in range(5)}
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols) == (len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", t or "")))
        assert (r.n_dup_lines, r.n_repeat_words) == (len(lines) - len(set(lines)), len(repeat))
        assert r.base_failed == (len(words) < 10 or 100 * len(repeat) > 20 * len(words)) and not (r.kept and r.base_failed)


def test_op2_thresholds_follow_the_group(spark):
    """A measure that varies in a source gets a wide fence there and a narrow one elsewhere; flat measures get the grain."""
    draw = random.Random(4)
    docs = []
    for source, low, high in (("narrow", 4, 5), ("wide", 2, 16)):
        for _ in range(150):
            docs.append((len(docs), " ".join("x" * draw.randint(low, high) + f"{draw.randrange(9)}" for _ in range(1 if source == "" else 6)) + " a b c d e", "en", source))
    df = spark.createDataFrame(docs, "doc_id long, text string, lang string, source string")
    limits = {r._source: r for r in quality.thresholds(quality.with_ratios(quality.measured(df))).collect()}
    assert limits["wide"].most_word_length_x100 > limits["narrow"].most_word_length_x100 + 300
    assert limits["wide"].most_symbols_per_mille == limits["narrow"].most_symbols_per_mille == quality.REACH * quality.GRAIN["symbols_per_mille"]


def test_op3(spark, sf, texts):
    assign = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
    got = rows(spark, sf, 3)
    assert set(got) == set(texts)
    for i, t in texts.items():
        t = t or ""
        found = [("assign", *m.span()) for m in assign.finditer(t) if len(m[2]) >= 6]
        found += [("access", *m.span()) for m in re.finditer("AKIA[A-Z0-9]+", t) if len(m[0]) >= 20]
        found += [("hex", *m.span()) for m in re.finditer("[0-9a-f]+", t) if len(m[0]) >= 24]
        found.sort(key=lambda s: (s[1], ("assign", "access", "hex").index(s[0])))
        r = got[i]
        assert (r.n_assign, r.n_access, r.n_hex) == tuple(sum(s[0] == k for s in found) for k in ("assign", "access", "hex"))
        assert r.base_sha256 == sha(spans_of(("assign", "access", "hex"), found))
        assert set(filter(None, spans_of(("assign", "access", "hex"), found).split(","))) <= set(r.spans.split(","))


def test_op4(spark, sf, texts):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(queries.vocabulary("word_bpe_49k.json"))
    ids = sorted(texts)
    want = [len(e.ids) for e in library.encode_batch([texts[i] or "" for i in ids], add_special_tokens=False)]
    got = rows(spark, sf, 4)
    for i, n in zip(ids, want, strict=True):
        assert (got[i].n_bytes, got[i].n_tokens, got[i].over_limit) == (len((texts[i] or "").encode()), n, n > 2048)


def test_op4_chunks_and_full_tables(monkeypatch):
    """Chunks of any size, and tables that fill up inside a text, change no count."""
    from tokenizers import Tokenizer

    path = queries.vocabulary("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    draw = random.Random(12)
    letters = "abst'rvlemd  \n'!?.0129éñßΣ\x1c\x85\xa0日本"
    odd = ["".join(draw.choices(letters, k=3000)) for _ in range(10)] + ["".join(draw.choices("abcdefgh", k=20_000)), " " * 500, "x" + " " * 500 + "y"]
    want = [len(e.ids) for e in library.encode_batch(odd, add_special_tokens=False)]
    counter = token_counts.Counter(open(path, encoding="utf-8").read())
    for chunk, section, states in ((1, 4, 10**6), (17, 8, 300), (500, 2, 10**6)):
        monkeypatch.setattr(token_counts, "CHUNK", chunk)
        monkeypatch.setattr(token_counts, "SECTION", section)
        monkeypatch.setattr(token_counts, "MOST_STATES", states)
        assert [counter.count(t) for t in odd] == want


def test_op5(spark, sf, texts):
    import public_tokenizers
    import tiktoken

    from strata.llm.byte_bpe import parse_ranks

    with open(queries.vocabulary("byte_bpe_multi_50k.tiktoken"), "rb") as f:
        library = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=parse_ranks(f), special_tokens={})
    got = rows(spark, sf, 5)
    assert set(got) == set(texts)
    for i, t in texts.items():
        ids = library.encode_ordinary(t or "")
        assert (got[i].n_tokens, got[i].ids_sha256, got[i].decoded_sha256) == (len(ids), sha(",".join(map(str, ids))), sha(t or ""))


def test_op6(spark, sf, texts):
    want = brute_components(list(texts.items()), 2)
    got = rows(spark, sf, 6)
    assert {i: r.component_id for i, r in got.items()} == want and all(r.kept == (i == r.component_id) for i, r in got.items())
    for i, t in texts.items():
        assert got[i].n_shingles == len(near_dup.shingle_set(t, 2))


@pytest.mark.parametrize("width", (2, 5))
def test_near_duplicates_lose_no_link_at_a_larger_size(spark, width):
    """All of sf0.1 against an exact join by prefixes of rare shingles."""
    import numpy as np

    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    sets = {r.doc_id: near_dup.shingle_set(r.text, width) for r in docs.select("doc_id", "text").collect()}
    up = {i: i for i in sets}

    def root(a):
        while up[a] != a:
            up[a] = up[up[a]]
            a = up[a]
        return a

    def join(a, b):
        a, b = root(a), root(b)
        up[max(a, b)] = min(a, b)

    heads: dict[bytes, int] = {}
    for i, s in sorted(sets.items()):
        if len(s):
            join(i, heads.setdefault(s.tobytes(), i))
    often = collections.Counter()
    for i in heads.values():
        often.update(sets[i].tolist())
    index = collections.defaultdict(list)
    for i in sorted(heads.values(), key=lambda i: len(sets[i])):
        s = sorted(sets[i].tolist(), key=lambda v: (often[v], v))
        prefix = s[: len(s) - math.ceil(0.8 * len(s) - 1e-9) + 1]
        for j in {j for v in prefix for j in index[v] if len(sets[j]) >= 0.8 * len(s) - 1e-9}:
            both = len(np.intersect1d(sets[i], sets[j], assume_unique=True))
            if 100 * both >= 80 * (len(s) + len(sets[j]) - both):
                join(i, j)
        for v in prefix:
            index[v].append(i)
    got = {r.doc_id: r.component_id for r in near_dup.near_duplicates(docs, width).collect()}
    assert got == {i: root(i) for i in sets}


def test_deduplicate_goes_by_rows(spark):
    """Ids that occur with several texts: each group keeps one row, and no text is lost."""
    x, w, z = "a b c d e f g h i j k l", "q w e r t y u i o p z", "m n b v c x z l k j"
    given = [(3, x), (5, w), (5, x), (7, z), (7, z), (8, None), (8, None), (None, x), (None, "a lone text without an id"), (None, "a lone text without an id")]
    df = spark.createDataFrame([(i, t, 1) for i, t in given], "doc_id long, text string, id int")
    got = sorted(((r.doc_id, r.text) for r in near_dup.deduplicate(df, 2).collect()), key=str)
    assert got == sorted([(3, x), (5, w), (7, z), (8, None), (8, None), (None, "a lone text without an id")], key=str)


def test_op7(spark, sf, texts):
    got = rows(spark, sf, 7)
    assert set(got) == set(texts)
    sizes, slots = collections.Counter(), collections.defaultdict(list)
    for i, r in got.items():
        raw = (texts[i] or "").encode()
        assert (r.size, r.text_crc32, r.law, r.grown_shard) == (len(raw) + 1, zlib.crc32(raw), "bytes", None)
        sizes[r.shard] += r.size
        slots[r.shard].append(r.slot)
    assert sorted(sizes) == list(range(8)) and all(sorted(s) == list(range(len(s))) for s in slots.values())
    assert max(sizes.values()) - min(sizes.values()) < 2 * max(r.size for r in got.values())


def test_equal_rows_are_spread_over_shards(spark):
    """600 of 1000 rows of equal size are one row repeated; shards are of nearly equal bytes all the same."""
    df = spark.createDataFrame([(7 if k < 600 else k, "the same text", "en", "a") for k in range(1000)], "doc_id long, text string, lang string, source string").repartition(3)
    got = kd_shards.shard(df, 8).collect()
    per = collections.Counter(r.shard for r in got)
    assert len(per) == 8 and max(per.values()) - min(per.values()) <= 4
    for k in per:
        assert sorted(r.slot for r in got if r.shard == k) == list(range(per[k]))


def test_op8(spark, sf, texts):
    def luhn(d):
        return sum(int(c) if k % 2 == 0 else 2 * int(c) - 9 * (c > "4") for k, c in enumerate(reversed(d))) % 10 == 0

    patterns = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
    got = rows(spark, sf, 8)
    assert set(got) == set(texts)
    for i, t in texts.items():
        found = []
        for kind, p in patterns.items():
            for m in re.finditer(p, t or ""):
                d = re.sub("[^0-9]", "", m[0])
                if kind == "ip" and max(map(int, m[0].split("."))) > 255 or kind == "card" and not (16 <= len(d) <= 19 and luhn(d)) or kind == "phone" and not 8 <= len(d) <= 15:
                    continue
                found.append((kind, *m.span()))
        r = got[i]
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(sum(s[0] == k for s in found) for k in patterns)
        assert r.base_sha256 == sha(spans_of(tuple(patterns), found)) and r.spans.startswith(spans_of(tuple(patterns), found))
        assert r.n_spans == len(found) + r.n_added == len(list(filter(None, r.spans.split(","))))


def test_op9(spark, sf, texts):
    items = {r.item_id: decontaminate.plain(r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()}
    got = rows(spark, sf, 9)
    assert set(got) == set(texts)
    for i, t in texts.items():
        whole = {k for k, item in items.items() if item in decontaminate.plain(t)}
        assert set(got[i].item_ids) >= whole and got[i].contaminated == bool(got[i].item_ids)


def test_edited_units_by_brute_force():
    """Every text within a unit's budget is found and none beyond it, by the whole distance table."""
    draw = random.Random(13)
    unit = "which of the seven rivers of the northern plain reaches the sea last"
    matcher = decontaminate.Matcher([(1, unit)], **decontaminate.SETTINGS)
    budget = max(k for _, _, k in matcher.units)
    for _ in range(150):
        changed = list(unit)
        for _ in range(draw.randint(0, 2 * budget + 1)):
            at = draw.randrange(len(changed))
            changed[at : at + 1] = draw.choice(([], ["q"], [changed[at], "x"]))
        text = "before it " + "".join(changed) + " and after"
        best = edit(unit, decontaminate.plain(text))
        assert matcher.find(text) == ({1: best} if best <= budget else {}), text


def test_short_items_are_found_as_words(spark):
    items = spark.createDataFrame([(1, "Paris"), (2, "what is it?"), (3, None), (4, " ")], "item_id long, text string")
    docs = spark.createDataFrame(list(enumerate(["I love  paris.", "paris", "comparison", "so What is\nit? yes", None, ""])), "doc_id long, text string")
    got = {r.doc_id: r.item_ids for r in decontaminate.find_items(docs, items).collect()}
    assert got == {0: [], 1: [1], 2: [], 3: [2], 4: [], 5: []}


def test_op10(spark, sf, texts):
    held = {i: zlib.crc32(str(i).encode()) % 7 == 2 for i in texts}
    c = collections.Counter()
    for i, t in texts.items():
        if not held[i]:
            c.update([*mixing.tokens(t), b""])
    n, v = sum(c.values()), len(c)
    got = rows(spark, sf, 10)
    assert set(got) == set(texts)
    for i, t in texts.items():
        words, r = [*mixing.tokens(t), b""], got[i]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[i], len(words), sum(c[w] > 0 for w in words), n)
        assert math.isclose(r.base_score, sum(math.log10((c[w] + 1) / (n + v + 1)) for w in words), rel_tol=1e-9)
        assert r.score < 0 and math.isclose(r.bits_per_byte, -r.score / math.log10(2) / sum(len(w) + 1 for w in words), rel_tol=1e-9)


def test_turns_by_counted_tokens(spark):
    """A tokenizer's counts decide where windows end; a null count falls back on the estimate."""
    from strata.llm import chat

    rows = [(1, k, "user" if k % 2 == 0 else "assistant", "word " * 10, 900 if k < 4 else None) for k in range(8)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, n long")
    by_count = chat.windows(df, tokens_column="n").orderBy("window").collect()
    by_bytes = chat.windows(df).collect()
    assert len(by_bytes) == 1 and len(by_count) >= 3 and all(r.tokens <= 2048 or r.over_budget for r in by_count)
    assert sum(r.n_turns - r.n_repeated for r in by_count) == 8
