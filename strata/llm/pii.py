"""Personal data: fixed rules, and boosted trees over the proposals of wide generators.

The rules give e-mail addresses, IP addresses, card and telephone numbers. Beyond them,
generators of high recall propose spans of what the rules leave, which may overlap:
written-out addresses and any run of grouped digits. Boosted trees judge each proposal by
its format and its context. They are fitted on labelled samples: generated texts with
addresses, telephone and card numbers in forms that no rule takes, generated texts with
dates, prices, versions, serial and book numbers, and a bounded sample of the table's own
proposals, which count as harmless unless marked. A third of the samples is held out; on
it the scores are calibrated and the threshold, precision and recall are found. Proposals
whose calibrated probability reaches the threshold are added, the better one where two
overlap.

Only DataFrame functions are used: the fitted trees become a CASE expression, and each
row is judged by itself, with no shuffle. Texts are cut into matches and what lies between
them once, and offsets are summed over chunks of matches, so time grows with a text's
length and not with its square.

Defined results: null counts as the empty text, which has no spans; texts are scanned
whole; repeated rows are scanned each; an empty table gives an empty result; further
columns are ignored. Offsets count code points.
"""

from __future__ import annotations

import math
import random
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The rules' patterns. Written with possessive repeats and anchored at the only places
#: where a match can begin, they find what the plain forms find, in linear time and constant stack.
EMAIL = r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
IP = r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"
CARD = r"[0-9](?:[\x20-]?[0-9])++"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
KINDS = ("email", "ip", "card", "phone")
#: Generators.
SPELLED = r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}\x20?(?:@|\(at\)|\[at\]|\x20at\x20)\x20?[A-Za-z0-9-]{1,63}(?:\x20?(?:\.|\(dot\)|\[dot\]|\x20dot\x20)\x20?[A-Za-z0-9-]{2,63}){1,5}+"
NUMBER = r"\+?\(?[0-9](?:[\x20()./-]{0,2}[0-9]){6,}+"
PROPOSED = ("email_like", "number_like")
CLUES = r"(?i)(tel|phone|call|mobile|fax|mail|card|visa|iban|account)[^0-9A-Za-z]*$"
#: What marks a written-out address as one: a bracketed or spelled mark, or a common ending.
MARKED = r"(?i)[(\[](at|dot)[)\]]|\x20dot\x20|\.(com|org|net|edu|gov|info|io|co|de|fr|es|uk|eu)$"
FEATURES = ("generator", "digits", "separators", "plus", "luhn", "at", "parens", "dots", "before", "after", "clue", "length", "octets")


SPAN = "array<struct<start:int,s:string,left:string,right:string>>"
#: Matches whose offsets are summed together before they join the others.
CHUNK = 256
#: What stands for each character of a rule's span where proposals are made.
HIDDEN = "\x01"


def bound(value: Column, body) -> Column:
    """`body` of a value that is worked out once."""
    return F.transform(F.array(value), body)[0]


def located(text: Column, pattern: str, may: Column) -> Column:
    """The matches as an array of (start, s, left, right): the up to 20 characters since the last match, and the one
    after. `may` is a cheap test that texts with a match pass."""
    empty = F.array().cast(SPAN)

    def put(acc, x):
        start = acc["at"] + F.length(x["p"])
        one = F.struct(start.cast("int").alias("start"), x["m"].alias("s"), F.right(x["p"], F.lit(20)).alias("left"), F.left(x["q"], F.lit(1)).alias("right"))
        return F.struct((start + F.length(x["m"])).cast("int").alias("at"), F.concat(acc["out"], F.array(one)).alias("out"))

    def add(acc, part):
        done = F.aggregate(part, F.struct(acc["at"].alias("at"), empty.alias("out")), put)
        return bound(done, lambda d: F.struct(d["at"].alias("at"), F.concat(acc["out"], F.array(d["out"])).alias("out")))

    def joined(pieces):
        matches = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
        sides = F.zip_with(F.slice(pieces, 1, F.size(pieces) - 1), F.slice(pieces, 2, F.size(pieces)), lambda p, q: F.struct(p.alias("p"), q.alias("q")))
        zipped = F.zip_with(matches, sides, lambda m, x: F.struct(m.alias("m"), x["p"].alias("p"), x["q"].alias("q")))
        parts = bound(zipped, lambda z: F.transform(F.sequence(F.lit(0), F.greatest(F.floor((F.size(z) - 1) / CHUNK), F.lit(0)).cast("int")), lambda k: F.slice(z, k * CHUNK + 1, F.lit(CHUNK))))
        start = F.struct(F.lit(0).alias("at"), F.array().cast(f"array<{SPAN}>").alias("out"))
        return F.aggregate(parts, start, add, lambda acc: F.flatten(acc["out"]))

    return F.when(may, bound(F.split(text, pattern, -1), joined)).otherwise(empty)


def unruled(text: Column) -> Column:
    """The text with the characters of all rules' spans hidden."""

    def hidden(kind):
        pattern, may, keep = RULES[kind]

        def hide(t):
            matches, pieces = F.regexp_extract_all(t, F.lit(pattern), F.lit(0)), F.split(t, pattern, -1)
            shown = F.zip_with(pieces, matches, lambda p, m: F.concat(p, F.coalesce(F.when(keep(m), F.repeat(F.lit(HIDDEN), F.length(m))).otherwise(m), F.lit(""))))
            return F.when(may(t), F.array_join(shown, "")).otherwise(t)

        return hide

    for kind in KINDS:
        text = bound(text, hidden(kind))
    return text


def digits_of(s: Column) -> Column:
    return F.regexp_replace(s, "[^0-9]", "")


def luhn(d: Column) -> Column:
    """Whether a digit string of up to 24 digits passes the check sum."""
    n = F.length(d)

    def worth(k):
        x = F.substring(d, k, F.lit(1)).try_cast("int")
        return F.when((n - k) % 2 == 0, x).otherwise(2 * x - F.when(x > 4, 9).otherwise(0))

    total = F.aggregate(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), F.lit(0), lambda a, k: a + F.coalesce(worth(k), F.lit(0)))
    return F.when(n <= 24, total % 10 == 0).otherwise(False)


def octets_fit(s: Column) -> Column:
    return F.forall(F.split(s, r"\."), lambda p: p.rlike("^0*[0-9]{1,3}$") & F.coalesce(F.substring(p, -3, 3).try_cast("int") <= 255, F.lit(False)))


def _digits(s: Column) -> Column:
    return F.length(digits_of(s))


#: By kind: the pattern, a test that texts with a match pass, and what a match must fulfil.
RULES = {
    "email": (EMAIL, lambda t: t.contains("@"), lambda s: F.lit(True)),
    "ip": (IP, lambda t: t.rlike(r"[0-9]\.[0-9]"), octets_fit),
    "card": (CARD, lambda t: t.rlike(r"[0-9][\x20-]?[0-9]"), lambda s: _digits(s).between(16, 19) & luhn(digits_of(s))),
    "phone": (PHONE, lambda t: t.contains("+") & t.rlike("[0-9]"), lambda s: _digits(s).between(8, 15)),
}


def rule_spans(text: Column) -> Column:
    """Array of (kind, start, end), by kind as listed, then start."""

    def spans(kind):
        pattern, may, keep = RULES[kind]
        found = F.filter(located(text, pattern, may(text)), lambda x: keep(x["s"]))
        return F.transform(found, lambda x: F.struct(F.lit(kind).alias("kind"), x["start"].alias("start"), (x["start"] + F.length(x["s"])).cast("int").alias("end")))

    return F.concat(*map(spans, KINDS))


def proposals(text: Column) -> Column:
    """Array of (kind, start, end, and the features as small integers), of what the rules leave."""

    def side(c):
        return F.when(F.coalesce(c, F.lit("")) == "", 0).when(c.rlike(r"\s"), 0).when(c.rlike(r"\p{L}"), 1).when(c.rlike(r"\p{N}"), 2).otherwise(3)

    def described(generator, found):
        def one(x):
            s, d = x["s"], digits_of(x["s"])
            count = lambda p: F.length(s) - F.length(F.regexp_replace(s, p, ""))
            end = (x["start"] + F.length(s)).cast("int")
            value = {
                "generator": F.lit(generator), "digits": F.least(F.length(d), F.lit(24)), "separators": F.least(count(r"[\x20()./-]"), F.lit(10)), "plus": s.startswith("+").cast("int"),
                "luhn": luhn(d).cast("int"), "at": s.contains("@").cast("int"), "parens": s.contains("(").cast("int"), "dots": F.least(count(r"\."), F.lit(6)),
                "before": side(F.right(x["left"], F.lit(1))), "after": side(x["right"]),
                "clue": ((s.rlike(MARKED) & ~s.contains("@")) if generator == 0 else x["left"].rlike(CLUES)).cast("int"), "length": F.least(F.length(s), F.lit(40)), "octets": (s.rlike(r"^[0-9]+(\.[0-9]+){3}$") & octets_fit(s)).cast("int"),
            }
            return F.struct(F.lit(PROPOSED[generator]).alias("kind"), x["start"].alias("start"), end.alias("end"), *(value[f].cast("int").alias(f) for f in FEATURES))

        return F.transform(found, one)

    def both(t):
        spelled = t.contains("@") | t.contains("(at)") | t.contains("[at]") | t.contains(" at ")
        return F.concat(described(0, located(t, SPELLED, spelled)), described(1, located(t, NUMBER, t.rlike(r"[0-9][\x20()./-]{0,2}[0-9]"))))

    return bound(unruled(text), both)


def overlaps(a: Column, b: Column) -> Column:
    return (a["start"] < b["end"]) & (b["start"] < a["end"])


@dataclass
class Trees:
    """Boosted trees of two levels: each is (feature, cut, left, right), where left and right are (feature, cut, low, high)."""

    bias: float = 0.0
    trees: list[tuple] = field(default_factory=list)
    threshold: float = math.inf
    #: On the samples held out: of what reaches the threshold, and of what should.
    precision: float = math.nan
    recall: float = math.nan

    def raw(self, x) -> float:
        total = self.bias
        for f, cut, *sides in self.trees:
            g, at, low, high = sides[x[f] > cut]
            total += high if x[g] > at else low
        return total

    def column(self, c: Column) -> Column:
        """The same sum as an expression over a struct of features."""
        total = F.lit(self.bias)
        for f, cut, *sides in self.trees:
            low, high = (F.when(c[FEATURES[g]] > at, hi).otherwise(lo) for g, at, lo, hi in sides)
            total = total + F.when(c[FEATURES[f]] > cut, high).otherwise(low)
        return total


Rows = list[tuple[tuple[int, ...], int, int]]


def boost(rows: Rows, held: Rows | None = None, rounds: int = 24, rate: float = 0.3, wanted: float = 0.9, ridge: float = 1.0) -> Trees:
    """Logistic boosting by histograms over (features, count, positives), then isotonic calibration of the
    scores on the rows held out; `threshold` is the least score whose calibrated probability reaches `wanted`."""
    n, pos = sum(r[1] for r in rows), sum(r[2] for r in rows)
    if not n or not pos:
        return Trees()
    model = Trees(bias=math.log((pos + 1) / (n - pos + 1)))
    score = [model.bias] * len(rows)
    width = len(FEATURES)

    def best(index, slopes):
        """The split of most gain, with its two leaf values."""
        g, h = sum(slopes[k][0] for k in index), sum(slopes[k][1] for k in index)
        flat = -rate * g / (h + ridge)
        top = (0.0, 0, 1 << 30, flat, flat)
        for f in range(width):
            sums: dict[int, list[float]] = {}
            for k in index:
                s = sums.setdefault(rows[k][0][f], [0.0, 0.0])
                s[0] += slopes[k][0]
                s[1] += slopes[k][1]
            gl = hl = 0.0
            for v in sorted(sums)[:-1]:
                gl, hl = gl + sums[v][0], hl + sums[v][1]
                gain = gl * gl / (hl + ridge) + (g - gl) ** 2 / (h - hl + ridge) - g * g / (h + ridge)
                if gain > top[0] + 1e-9:
                    top = (gain, f, v, -rate * gl / (hl + ridge), -rate * (g - gl) / (h - hl + ridge))
        return top

    for _ in range(rounds):
        p = [1 / (1 + math.exp(-max(-30.0, min(30.0, s)))) for s in score]
        slopes = [(r[1] * q - r[2], r[1] * q * (1 - q)) for r, q in zip(rows, p, strict=True)]
        every = range(len(rows))
        _, f, cut, _, _ = best(every, slopes)
        sides = [best([k for k in every if (rows[k][0][f] > cut) == upper], slopes)[1:] for upper in (False, True)]
        model.trees.append((f, cut, *sides))
        for k in every:
            g, at, low, high = sides[rows[k][0][f] > cut]
            score[k] += high if rows[k][0][g] > at else low
    held = rows if held is None else held
    scores = [model.raw(r[0]) for r in held]
    pools: list[list[float]] = []  # least score, count, positives
    for s, k in sorted(zip(scores, range(len(held)), strict=True)):
        pools.append([s, held[k][1], held[k][2]])
        while len(pools) > 1 and pools[-2][2] * pools[-1][1] >= pools[-1][2] * pools[-2][1]:
            last = pools.pop()
            pools[-1][1] += last[1]
            pools[-1][2] += last[2]
    model.threshold = next((s - 1e-9 for s, count, positives in pools if positives >= wanted * count), math.inf)
    reached = [r for s, r in zip(scores, held, strict=True) if s >= model.threshold]
    hits = sum(r[2] for r in reached)
    model.precision = hits / n if (n := sum(r[1] for r in reached)) else math.nan
    model.recall = hits / n if (n := sum(r[2] for r in held)) else math.nan
    return model


def samples(count: int = 1_000) -> list[tuple[str, int]]:
    """Labelled texts by a fixed draw: `count` for each form, with one span of its own each."""
    draw = random.Random(8)
    word = lambda a, b: "".join(draw.choices("abcdefghijklmnopqrstuvwxyz", k=draw.randint(a, b)))
    digits = lambda n: "".join(draw.choices("0123456789", k=n))

    def address():
        at, dot = draw.choice(((" at ", "."), (" at ", " dot "), ("(at)", "."), (" (at) ", " (dot) "), ("[at]", "[dot]"), (" [at] ", " [dot] "), ("(at)", "(dot)")))
        name = word(2, 10) + draw.choice(("", "", f".{word(2, 8)}", str(draw.randint(1, 99))))
        return f"{name}{at}{word(3, 10)}{dot}{draw.choice(('com', 'org', 'net', 'edu', 'info', 'de', 'fr', 'es'))}"

    def telephone():
        a, b, c = digits(3), digits(3), digits(4)
        number = draw.choice((f"({a}) {b}-{c}", f"{a}-{b}-{c}", f"{a}.{b}.{c}", f"{a} {b} {c}", f"0{a}/{b}{c}", f"00{digits(2)} {a} {b} {c}"))
        return draw.choice(("call ", "tel. ", "phone: ", "mobile ", "fax: ")) + number

    def card():
        n = [draw.randrange(10) for _ in range(15)]
        total = sum(x if k % 2 else 2 * x - 9 * (x > 4) for k, x in enumerate(n))
        n = "".join(map(str, [*n, -total % 10]))
        return draw.choice(("card ", "visa: ", "account ")) + draw.choice(".- /").join((n[:4], n[4:8], n[8:12], n[12:])).replace("- ", "-")

    def date():
        y, m, d = draw.randint(1900, 2030), draw.randint(1, 12), draw.randint(1, 28)
        return draw.choice((f"{y}-{m:02}-{d:02}", f"{d:02}.{m:02}.{y}", f"{d:02}/{m:02}/{y}", f"{y}{m:02}{d:02}", f"{y} - {y + 3}"))

    def figure():
        return draw.choice((f"{draw.randint(1, 99)} {digits(3)} {digits(3)}", f"{digits(7)}.{digits(2)}", f"{digits(2)}.{digits(4)} {digits(2)}.{digits(4)}", f"{digits(1)}.{digits(2)}.{digits(3)}.{digits(2)}.{digits(4)}"))

    def serial():
        return draw.choice((digits(draw.randint(7, 18)), f"978-{digits(1)}-{digits(2)}-{digits(6)}-{digits(1)}", f"{digits(4)}-{digits(4)}", f"{digits(5)}/{digits(4)}", digits(draw.randint(20, 40))))

    def place():
        return f"{word(3, 8)} at {word(3, 8)}.{word(4, 8)}"

    made = [(f"{word(2, 8)}, {form()}, {word(2, 8)}", label) for form, label in ((address, 1), (telephone, 1), (card, 1), (date, 0), (figure, 0), (serial, 0), (place, 0)) for _ in range(count)]
    return made


def fit(docs: DataFrame, sample: int = 20_000, id_column: str = "doc_id", text_column: str = "text") -> Trees:
    """Trees from `samples` and, as harmless, at most `sample` unmarked proposals of the table, chosen by hash. A third of
    either is held out for calibration. Only counts by feature values reach the driver."""
    text = F.coalesce(F.col(text_column), F.lit(""))
    one = docs.select(F.col(id_column).alias("id"), F.explode(proposals(text)).alias("c")).select("c.*", F.xxhash64("id", "c.start", "c.kind").alias("h"))
    taken = one.filter("clue = 0 and parens = 0").orderBy("h", "start", "kind").limit(sample)
    table = taken.groupBy((F.pmod("h", F.lit(3)) == 0).alias("held"), *FEATURES).agg(F.count("*").alias("n"), F.lit(0).cast("long").alias("pos")).collect()
    made = docs.sparkSession.createDataFrame([(k, t, label) for k, (t, label) in enumerate(samples())], "k long, text string, label long")
    made = made.select("k", "label", F.explode(proposals(F.col("text"))).alias("c")).select("k", "label", "c.*")
    more = made.groupBy((F.col("k") % 3 == 0).alias("held"), *FEATURES).agg(F.count("*").alias("n"), F.sum("label").alias("pos")).collect()
    rows = {held: sorted((tuple(r[f] for f in FEATURES), r["n"], r["pos"]) for r in [*table, *more] if r["held"] == held) for held in (False, True)}
    return boost(rows[False], rows[True])


def find(docs: DataFrame, model: Trees, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """One row per document: id, `rules` and `added`, arrays of (kind, start, end)."""
    text = F.coalesce(F.col(text_column), F.lit(""))
    span = "array<struct<kind:string,start:int,end:int>>"
    if not model.trees or model.threshold == math.inf:
        return docs.select(id_column, rule_spans(text).alias("rules"), F.array().cast(span).alias("added"))
    scored = F.transform(proposals(text), lambda c: F.struct(model.column(c).alias("score"), c["kind"].alias("kind"), c["start"].alias("start"), c["end"].alias("end")))
    d = docs.select(F.col(id_column), rule_spans(text).alias("rules"), F.filter(scored, lambda c: c["score"] >= model.threshold).alias("good"))
    better = lambda a, b: (a["score"] > b["score"]) | ((a["score"] == b["score"]) & (a["kind"] < b["kind"]))
    # a generator's own proposals do not overlap
    several = F.size(F.array_distinct(F.transform("good", lambda c: c["kind"]))) > 1
    best = F.when(several, F.filter("good", lambda c: ~F.exists("good", lambda o: overlaps(o, c) & better(o, c)))).otherwise(F.col("good"))
    return d.select(id_column, "rules", F.transform(best, lambda c: F.struct(c["kind"].alias("kind"), c["start"].alias("start"), c["end"].alias("end"))).alias("added"))


def digest(spans: Column) -> Column:
    """`kind:start:end`, comma-joined."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
