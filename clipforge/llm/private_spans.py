"""Personal data by boosted trees over candidate spans, in DataFrame functions only.

Base spans are fixed patterns with checks (a Luhn sum, octets, digit counts).
Looser generators propose further, overlapping spans. Format and context of each
proposal make a small vector of binned features; what defines the base pattern of
a kind (the plus sign of a phone) is not among them. Learnt from are

* proposals that are a checked base span: positive;
* others that pass their kind's check when read without disguise, but reach into
  a checked span or follow a word such as "version" or "token": negative;
* for each of both a copy with the features of a reformatted span (``COPIES``),
  so a format that the base pattern never has does not speak against a span.

Other proposals are not labelled, only rated. All proposals of the corpus are
aggregated to distinct vectors, so the trees are boosted on the driver over a
table bounded by the number of bins (at most 23,040 cells) while every row
counts. The trees are one CASE expression. A threshold per kind is the lowest at
which precision on the held-out fifth of the texts is at least ``PRECISION``.

Base spans always stay. Proposals that pass the threshold and their check and
overlap no base span are added; of those that overlap each other the first, at
one place the better. Work is in proportion to the text and the number of
matches: running sums over matches go by blocks (``_running``).

Null texts count as empty and give no spans. Rows that repeat are each scanned.
Ties go to the kind listed first. An empty table gives no rows. Other columns
pass through ``find_private``; columns named like the added ones are replaced.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialize, table

KINDS = ("email", "ip", "card", "phone")
PRECISION = 0.95
ROUNDS, DEPTH, RATE = 16, 3, 0.4

# The base patterns, leftmost and non-overlapping. Matches start where a run starts
# or where the last match ended, and runs are possessive, so no text takes quadratic time.
BASE = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
# What a text must hold for a pattern to be tried at all.
GATE = {"email": "@", "ip": r"[0-9]\.[0-9]", "card": r"[0-9][\x20-]?[0-9]", "phone": r"\+[0-9]"}
# The generators, looser than the base.
LOOSE = {
    "email": r"(?:\G|(?<![\p{L}0-9._%+-]))[\p{L}0-9._%+-]++\x20?(?:@|\(at\)|\[at\])\x20?[\p{L}0-9-]++(?:\x20?(?:\.|\(dot\)|\[dot\])\x20?[\p{L}0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++(?:\x20?\.\x20?[0-9]++){3}",
    "card": r"[0-9](?:[\x20.-]{0,2}[0-9])++",
    "phone": r"(?:\G|(?<![0-9+]))\+?[0-9(](?:[\x20()./-]{0,3}[0-9])++",
}
LOOSE_GATE = {"email": r"@|\(at\)|\[at\]", "ip": r"[0-9]\x20?\.", "card": r"[0-9][\x20.-]{0,2}[0-9]", "phone": r"[0-9(][\x20()./-]{0,3}[0-9]"}
CONTEXT = r"(?i)(mail|contact|phone|tel|call|fax|mobile|card|visa|credit|server|host|address|\bip\b)"
NEGATIVE = r"(?i)(token|version|key|secret|hash|isbn|order|id)[\x20\"'=:#]*$"
# A credential and its name, counted beside the four kinds.
SECRET = r"""(?i)(?:token|secret|api[_-]?key|passw(?:or)?d)["']?\x20?[=:]\x20?["']?[A-Za-z0-9_/+-]{16,}"""
SECRET_WORDS = ("token", "secret", "key", "passw")
BLOCK, CONTEXT_LENGTH = 64, 24
FAR = (1 << 31) - 1


def _with(value: Column, use) -> Column:
    """``use(value)`` with the value computed once."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _running(values: Column, join, zero: int) -> Column:
    """What the values up to each place come to under ``join``; by blocks, so no long array is copied for every value."""
    none = F.array().cast("array<int>")
    first = F.struct(F.lit(zero).alias("at"), none.alias("out"))

    def upto(acc: Column, x: Column) -> Column:
        return F.struct(join(acc["at"], x).alias("at"), F.concat(acc["out"], F.array(join(acc["at"], x))).alias("out"))

    def before(acc: Column, x: Column) -> Column:
        return F.struct(join(acc["at"], x).alias("at"), F.concat(acc["out"], F.array(acc["at"])).alias("out"))

    def blocks(all_: Column) -> Column:
        count = F.greatest(F.ceil(F.size(all_) / F.lit(BLOCK)).cast("int") - 1, F.lit(0))
        return F.transform(F.sequence(F.lit(0), count), lambda b: F.aggregate(F.slice(all_, b * BLOCK + 1, BLOCK), first, upto, lambda acc: acc["out"]))

    def joined(parts: Column) -> Column:
        sums = F.transform(parts, lambda x: F.coalesce(F.try_element_at(x, F.lit(-1)), F.lit(zero)))
        return _with(F.aggregate(sums, first, before, lambda acc: acc["out"]), lambda offset: F.flatten(F.transform(parts, lambda x, b: F.transform(x, lambda v: join(F.get(offset, b), v)))))

    return _with(values, lambda all_: _with(blocks(all_), joined))


def _spans(text: Column, pattern: str, gate: str) -> Column:
    """Start (code points), end, text and surroundings of each match: matches and what stands between them give the places."""
    empty = F.array().cast("array<struct<start:int,end:int,hit:string,before:string,after:string>>")

    def placed(cut: Column) -> Column:
        hits, gaps = cut["hits"], cut["gaps"]
        steps = F.transform(hits, lambda h, i: F.length(h) + F.length(F.get(gaps, i)))

        def one(ends: Column):
            def span(h: Column, i: Column) -> Column:
                before = F.right(F.concat(F.coalesce(F.get(hits, i - 1), F.lit("")), F.get(gaps, i)), F.lit(CONTEXT_LENGTH))
                after = F.left(F.concat(F.get(gaps, i + 1), F.coalesce(F.get(hits, i + 1), F.lit(""))), F.lit(1))
                return F.struct((F.get(ends, i) - F.length(h)).alias("start"), F.get(ends, i).alias("end"), h.alias("hit"), before.alias("before"), after.alias("after"))

            return F.transform(hits, span)

        return _with(_running(steps, lambda a, b: a + b, 0), one)

    cut = F.struct(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("hits"), F.split(text, pattern, -1).alias("gaps"))
    return F.when(text.rlike(gate), _with(cut, placed)).otherwise(empty)


def _digits(hit: Column) -> Column:
    return F.regexp_replace(hit, r"[^0-9]", "")


def _luhn(digits: Column) -> Column:
    places = F.transform(F.split(F.reverse(digits), ""), lambda c, i: F.when(i % 2 == 0, c.cast("int")).otherwise(F.when(c.cast("int") > 4, c.cast("int") * 2 - 9).otherwise(c.cast("int") * 2)))
    return F.aggregate(F.filter(places, lambda x: x.isNotNull()), F.lit(0), lambda a, x: a + x) % 10 == 0


def _valid(kind: str, hit: Column) -> Column:
    if kind == "ip":
        return hit.rlike(r"^0*+(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9]|)(?:\.0*+(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9]|)){3}$")
    n = F.length(_digits(hit))
    if kind == "card":
        return n.between(13, 19) & F.when(n.between(13, 19), _luhn(_digits(hit))).otherwise(False)
    return n.between(9, 15) if kind == "phone" else F.lit(True)


def _plain(kind: str, hit: Column) -> Column:
    """What a proposal reads without its disguise, for the check."""
    if kind == "email":
        return F.regexp_replace(F.regexp_replace(F.regexp_replace(hit, r"\x20?(?:\(at\)|\[at\]|@)\x20?", "@"), r"\x20?(?:\(dot\)|\[dot\])\x20?", "."), r"\x20?\.\x20", ".")
    return F.replace(hit, F.lit(" "), F.lit("")) if kind == "ip" else hit


def _sound(kind: str, hit: Column) -> Column:
    """Whether a proposal passes the check of its kind."""
    plain = _plain(kind, hit)
    return plain.rlike(r"^[^@\x20]+@[^@\x20]+\.\p{L}{2,}$") if kind == "email" else _valid(kind, plain)


def _checked(kind: str) -> Column:
    return F.filter(f"base_{kind}", lambda s: _valid(kind, s["hit"]))


def with_base(docs: DataFrame, keep: tuple = ()) -> DataFrame:
    """row (all columns of ``docs``, or those of ``keep``), body and, for each kind, ``base_<kind>``: spans that pass their check."""
    row = F.struct(*[F.col(f"`{c}`") for c in keep or docs.columns])
    out = docs.select(row.alias("row"), F.coalesce(F.col("text"), F.lit("")).alias("body"))
    out = out.withColumns({f"base_{k}": _spans(F.col("body"), BASE[k], GATE[k]) for k in KINDS})
    return out.withColumns({f"base_{k}": _checked(k) for k in KINDS})


def features(kind: str, span: Column) -> dict[str, Column]:
    """Binned format and context of a proposal: small whole numbers."""
    hit, before = span["hit"], span["before"]

    def edge(c: Column) -> Column:
        return F.when(c == "", 0).when(c.rlike(r"\s"), 1).when(c.rlike(r"[\p{L}\p{N}_]"), 2).otherwise(3)

    def bins(x: Column, cuts: tuple) -> Column:
        out = F.lit(0)
        for c in cuts:
            out = out + (x >= c).cast("int")
        return out

    disguise = r"\((?:at|dot)\)|\[(?:at|dot)\]|\x20@|@\x20|\x20\.|\.\x20"
    return {
        "kind": F.lit(KINDS.index(kind)),
        "digits": bins(F.length(_digits(hit)), (1, 9, 13, 16, 20)),
        "groups": bins(F.regexp_count(hit, F.lit("[0-9]+")), (2, 3, 4, 5)),
        "marks": F.when(hit.rlike(disguise), 3).when(hit.rlike("[./]"), 2).when(hit.rlike(r"[\x20()-]"), 1).otherwise(0),
        "before": edge(F.right(before, F.lit(1))),
        "after": edge(span["after"]),
        "context": F.when(before.rlike(NEGATIVE), 2).when(before.rlike(CONTEXT), 1).otherwise(0),
    }


NAMES = ("kind", "digits", "groups", "marks", "before", "after", "context")
# What a reformatted span of a kind has instead: (feature, value to set or step to add).
COPIES = {"email": ("marks", 3, None), "ip": ("marks", 3, None), "card": ("marks", 2, None), "phone": ("groups", None, -1)}


def _described(kind: str) -> Column:
    """Proposals of a kind: place, features, whether they pass the check, and whether they are a checked base span."""
    def one(s: Column) -> Column:
        sound = _sound(kind, s["hit"])
        same = s["hit"].rlike(f"^(?:{BASE[kind]})$") & _valid(kind, s["hit"])
        return F.struct(s["start"].alias("start"), s["end"].alias("end"), sound.alias("sound"), same.alias("same"), *[v.cast("int").alias(n) for n, v in features(kind, s).items()])

    return F.transform(f"loose_{kind}", one)


def _bases() -> Column:
    return F.concat(*[_places(F.col(f"base_{k}")) for k in KINDS])


def _swept(proposals: Column, bases: Column) -> Column:
    """The proposals by start, with ``free``: no base span overlaps them. One sweep over both lists in order."""
    mark = lambda s, p: F.struct(s["start"].alias("start"), s["end"].alias("end"), p.alias("p"))
    none = F.lit(None)

    def swept(all_: Column) -> Column:
        is_base = lambda x: x["p"].isNull()
        ends = _running(F.transform(all_, lambda x: F.when(is_base(x), x["end"]).otherwise(0)), F.greatest, 0)
        starts = F.reverse(_running(F.reverse(F.transform(all_, lambda x: F.when(is_base(x), x["start"]).otherwise(FAR))), F.least, FAR))
        marked = lambda e: F.transform(all_, lambda x, i: F.struct(x["p"].alias("p"), ((F.get(e["ends"], i) <= x["start"]) & (F.get(e["starts"], i) >= x["end"])).alias("free")))
        return F.filter(_with(F.struct(ends.alias("ends"), starts.alias("starts")), marked), lambda x: x["p"].isNotNull())

    every = F.concat(F.transform(bases, lambda s: mark(s, none)), F.transform(proposals, lambda s: mark(s, s)))
    return F.when(F.size(proposals) > 0, _with(F.array_sort(every), swept))


def with_proposals(docs: DataFrame) -> DataFrame:
    """Adds ``proposals`` to ``with_base``: p (kind, place, features, checks) and free; null if there are none."""
    docs = docs.withColumns({f"loose_{k}": _spans(F.col("body"), LOOSE[k], LOOSE_GATE[k]) for k in KINDS})
    docs = docs.withColumn("proposals", F.concat(*[_described(k) for k in KINDS])).drop(*[f"loose_{k}" for k in KINDS])
    return docs.withColumn("proposals", _swept(F.col("proposals"), _bases()))


# --- boosting over the table of distinct vectors ---------------------------------------------

def _grow(rows: list, depth: int) -> dict:
    """A regression tree of Newton steps on (features, gradient, weight) sums."""
    g, h = sum(r[1] for r in rows), sum(r[2] for r in rows)
    leaf = {"value": RATE * g / (h + 1.0)}
    if depth == 0:
        return leaf
    best = None
    for f in range(len(NAMES)):
        for cut in sorted({r[0][f] for r in rows})[1:]:
            gl, hl = sum(r[1] for r in rows if r[0][f] < cut), sum(r[2] for r in rows if r[0][f] < cut)
            gain = gl * gl / (hl + 1) + (g - gl) ** 2 / (h - hl + 1) - g * g / (h + 1)
            if gain > 1e-6 and (best is None or gain > best[0]):
                best = (gain, f, cut)
    if best is None:
        return leaf
    _, f, cut = best
    return {"feature": f, "cut": cut, "low": _grow([r for r in rows if r[0][f] < cut], depth - 1), "high": _grow([r for r in rows if r[0][f] >= cut], depth - 1)}


def tree_value(tree: dict, x: tuple) -> float:
    while "value" not in tree:
        tree = tree["low"] if x[tree["feature"]] < tree["cut"] else tree["high"]
    return tree["value"]


def boost(cells: list[tuple[tuple, int, int]]) -> list[dict]:
    """Trees for logistic loss; a cell is (features, positives, all)."""
    margin, trees = [0.0] * len(cells), []
    for _ in range(ROUNDS if cells else 0):
        rows = []
        for (x, pos, n), m in zip(cells, margin, strict=True):
            p = 1 / (1 + math.exp(-m))
            rows.append((x, pos - n * p, n * p * (1 - p)))
        tree = _grow(rows, DEPTH)
        trees.append(tree)
        margin = [m + tree_value(tree, x) for (x, _, _), m in zip(cells, margin, strict=True)]
    return trees


def _case(tree: dict, s: Column) -> Column:
    if "value" in tree:
        return F.lit(float(tree["value"]))
    return F.when(s[NAMES[tree["feature"]]] < tree["cut"], _case(tree["low"], s)).otherwise(_case(tree["high"], s))


def thresholds(trees: list[dict], held: list[tuple[tuple, int, int]]) -> dict[int, float]:
    """Per kind the lowest margin whose held-out precision is high enough; kinds without one are left out."""
    out = {}
    for k in range(len(KINDS)):
        scored = sorted(((sum(tree_value(t, x) for t in trees), pos, n) for x, pos, n in held if x[0] == k), reverse=True)
        pos = n = 0
        for i, (m, p, c) in enumerate(scored):
            pos, n = pos + p, n + c
            if (i + 1 == len(scored) or scored[i + 1][0] < m) and pos >= PRECISION * n:
                out[k] = m
    return out


def _copied(kind: int, x: tuple) -> tuple:
    name, value, step = COPIES[KINDS[kind]]
    at = NAMES.index(name)
    return (*x[:at], max(0, x[at] + step) if value is None else value, *x[at + 1:])


def cells_of(rows: list[tuple]) -> list[tuple[tuple, int, int]]:
    """(features, positives, all) of labelled (features, positives, negatives), each with its reformatted copy."""
    cells: dict = {}
    for x, pos, neg in rows:
        for y in (x, _copied(x[0], x)):
            p, n = cells.get(y, (0, 0))
            cells[y] = (p + pos, n + pos + neg)
    return [(x, p, n) for x, (p, n) in sorted(cells.items()) if n]


def train(proposed: DataFrame) -> tuple[list[dict], dict[int, float]]:
    cell = proposed.select(F.col("held"), F.explode("proposals").alias("s")).select("held", "s.free", "s.p.*")
    negative = ~F.col("same") & F.col("sound") & (~F.col("free") | (F.col("context") == 2))
    table_ = cell.groupBy("held", *NAMES).agg(F.count_if("same").alias("pos"), F.count_if(negative).alias("neg")).collect()
    rows = sorted((r["held"], tuple(r[n] for n in NAMES), r["pos"], r["neg"]) for r in table_)
    trees = boost(cells_of([r[1:] for r in rows if not r[0]]))
    return trees, thresholds(trees, cells_of([r[1:] for r in rows if r[0]]))


def _with_held(proposed: DataFrame) -> DataFrame:
    return proposed.withColumn("held", F.crc32(F.col("body").cast("binary")) % 5 == 0)


def select_spans(proposed: DataFrame, model: tuple[list[dict], dict[int, float]]) -> DataFrame:
    """Adds ``added``: the proposals that the trees select."""
    trees, least = model
    none = F.array().cast("array<struct<kind:int,start:int,end:int,margin:double>>")
    if not trees or not least:
        return proposed.withColumn("added", none)
    score = lambda s: sum((_case(t, s) for t in trees), F.lit(0.0))
    floor = F.create_map(*[F.lit(v) for k, m in least.items() for v in (k, float(m))])
    sound = F.filter(F.coalesce("proposals", F.lit(None).cast(proposed.schema["proposals"].dataType)), lambda x: x["free"] & x["p"]["sound"] & ~x["p"]["same"])
    scored = F.transform(sound, lambda x: F.struct(x["p"]["start"].alias("start"), (-score(x["p"])).alias("down"), x["p"]["kind"].alias("kind"), x["p"]["end"].alias("end")))
    passed = F.filter(scored, lambda s: -s["down"] >= F.coalesce(F.try_element_at(floor, s["kind"]), F.lit(float("inf"))))

    def first(all_: Column) -> Column:
        ends = _running(F.transform(all_, lambda s: s["end"]), F.greatest, 0)
        kept = lambda e: F.filter(all_, lambda s, i: (i == 0) | (F.get(e, i - 1) <= s["start"]))
        return F.transform(_with(ends, kept), lambda s: F.struct(s["kind"].alias("kind"), s["start"].alias("start"), s["end"].alias("end"), (-s["down"]).alias("margin")))

    return proposed.withColumn("added", F.coalesce(F.when(F.size("proposals") > 0, _with(F.array_sort(passed), first)), none))


def find_private(docs: DataFrame) -> DataFrame:
    """``docs`` with base_<kind> and ``added``, the spans (start, end) of the patterns and of the trees; two passes over the texts."""
    proposed = _with_held(with_proposals(with_base(docs)))
    found = select_spans(proposed, train(proposed))
    names = [*[f"base_{k}" for k in KINDS], "added"]
    return found.select(*[F.col("row")[c].alias(c) for c in docs.columns if c not in names], *names)


def redact(docs: DataFrame, mark: str = "[private]") -> DataFrame:
    """``docs`` with ``clean_text``: every base and added span replaced by ``mark``."""
    names = [c for c in docs.columns if c != "clean_text"]
    found = find_private(docs.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("kept"), "text"))
    body = F.coalesce(F.col("text"), F.lit(""))

    def cleaned(spans: Column) -> Column:
        """Spans that overlap are one; what stands between is joined by the mark."""
        def parts(ends: Column) -> Column:
            opens = F.filter(F.sequence(F.lit(0), F.size(spans) - 1), lambda i: (i == 0) | (F.get(ends, i - 1) <= F.get(spans, i)["start"]))
            return _with(opens, lambda o: F.array_join(F.transform(F.sequence(F.lit(0), F.size(o)), lambda k: piece(o, ends, k)), mark))

        def piece(o: Column, ends: Column, k: Column) -> Column:
            lo = F.when(k == 0, 0).otherwise(F.get(ends, F.coalesce(F.get(o, k), F.size(spans)) - 1))
            return F.substring(body, lo + 1, F.coalesce(F.get(spans, F.get(o, k))["start"], F.length(body)) - lo)

        return _with(_running(F.transform(spans, lambda s: s["end"]), F.greatest, 0), parts)

    spans = F.array_sort(F.concat(_bases(), _places(F.col("added"))))
    done = F.when(F.size(spans) == 0, body).otherwise(_with(spans, cleaned))
    return found.select("kept.*", done.alias("clean_text"))


def _listed(kind: str, spans: Column) -> Column:
    return F.transform(spans, lambda s: F.concat_ws(":", F.lit(kind), s["start"].cast("string"), s["end"].cast("string")))


def _places(spans: Column) -> Column:
    return F.transform(spans, lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end")))


def _of_kind(kind: str) -> Column:
    return F.filter("added", lambda s: s["kind"] == KINDS.index(kind))


def op9_private_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    secret = F.when(F.array_contains(F.transform(F.array(*map(F.lit, SECRET_WORDS)), lambda w: F.lower("body").contains(w)), True), F.regexp_count("body", F.lit(SECRET))).otherwise(0)
    proposed = _with_held(with_proposals(with_base(docs, ("doc_id",))))
    places = [_places(F.col(f"base_{k}")).alias(f"base_{k}") for k in KINDS]
    # places and features are little beside the texts: written once, so the patterns run once
    proposed = materialize(proposed.select(F.col("row.doc_id").alias("doc_id"), "held", "proposals", secret.cast("long").alias("n_secret"), *places), "private-proposals")
    found = select_spans(proposed, train(proposed))
    base = F.array_join(F.concat(*[_listed(k, F.col(f"base_{k}")) for k in KINDS]), ",")
    every = [_listed(k, F.array_sort(F.concat(F.col(f"base_{k}"), _places(_of_kind(k))))) for k in KINDS]
    counts = [F.size(f"base_{k}").cast("long").alias(f"n_{k}") for k in KINDS]
    added = F.size("added").cast("long")
    private = sum((F.size(f"base_{k}") for k in KINDS), added + F.col("n_secret"))
    return found.select("doc_id", *counts, F.sha2(base, 256).alias("base_sha256"), F.array_join(F.concat(*every), ",").alias("spans"), added.alias("n_added"), "n_secret", private.cast("long").alias("n_private"))
