"""Personal data by candidate gradient boosting, in DataFrame functions only.

1. Strict patterns give the *base* spans (validated e-mail addresses, IP addresses, cards and phone numbers).
2. Loose high-recall generators propose overlapping candidates: anything around an at-sign (also written out in
   brackets) and any run of digits and separators, the latter once for each numeric kind.
3. Boosted depth-2 trees score each candidate from flags of its format and of the words before it.  There are no labels
   for personal data, and the base spans can't serve, as only candidates that meet none may be added.  So the trees
   are fitted to *planted* texts, made in SQL by arithmetic: values in formats that the base patterns miss (written-out
   addresses, cards with other separators or a mistyped digit, phones without a plus) and decoys (dates, amounts, stamps,
   order numbers), with and without words that announce them.  The number of planted rows is a parameter; candidates are
   first counted by pattern of flags, so the fit sees a table of bounded size, and the model is one SQL expression.
4. Each kind's threshold is calibrated to a precision of `precision` on a quarter of the planted rows that the fit didn't
   see; candidates at or over it that meet no base span are added.  Whole formats take no part in fit and
   calibration: `quality` gives precision and recall of the added spans on those.  Neither depends on the corpus, so every
   row of every table is treated alike.

Positions count code points, ends exclusive. Null and empty texts have no spans. The trees never remove a base span.  Rows
are treated one by one: repeated and null doc_ids stay as they are.  `redacted` keeps all columns, also those named like the
ones made on the way; `digest` returns doc_id and its own columns only.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from erasureml.llm.core import read_table, reliable

PLANTED_ROWS = 40_000
KINDS = ("email", "ip", "card", "phone")
# The base patterns.  Those of the contract, written so that no position is scanned again: repeats whose
# end is decided take no backtracking (++), and a run that failed once isn't tried from its second character.
BASE = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[ -]?[0-9])++",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
}
GATE = {"email": "@", "ip": ".", "card": "", "phone": "+"}
LOOSE_AT = r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++ ?(?:@|\(at\)|\[at\]) ?[A-Za-z0-9-]++(?:(?:\.| ?\(dot\) ?| ?\[dot\] ?)[A-Za-z0-9-]++)*+"
LOOSE_NUMBER = r"[+(]?[0-9][0-9 ().-]{5,}[0-9]"
# Words that often stand before each kind, lower case.
CUES = {
    "email": "mail|e-mail|email|contact|write",
    "ip": "ip|host|server|address|addr",
    "card": "card|visa|mastercard|credit|pay",
    "phone": "phone|tel|telephone|call|fax|mobile|cell",
}
#: Words that often stand before other numbers.
OTHERWISE = "order|ref|id|no|version|total|page|invoice|serial|item|row|section|date|score|price|count|lot|at"
FLAGS = (
    "full_at", "written", "dotted", "short_tail", "plus", "bracket", "spaced", "dashed", "solid", "wide_gap", "fours", "bytes4", "three_three_four", "year_first", "zero_first", "luhn",
    "digits_7", "digits_8_9", "digits_10", "digits_11_15", "digits_16_19", "glued_left", "glued_right", "cue", "otherwise",
)


def _lit(pattern: str) -> str:
    return "r'" + pattern.replace("'", "\\'") + "'"


def located(text: str, pattern: str, gate: str) -> str:
    """SQL: array of (s, e, m) of all matches, leftmost and non-overlapping, from the pieces between them."""
    p = _lit(pattern)
    pairs = f"arrays_zip(transform(split({text}, {p}, -1), x -> length(x)), regexp_extract_all({text}, {p}, 0))"
    step = (
        "(a, x) -> if(x['1'] is null, a, named_struct('at', a.at + x['0'] + length(x['1']), "
        "'out', array_append(a.out, named_struct('s', a.at + x['0'], 'e', a.at + x['0'] + length(x['1']), 'm', x['1']))))"
    )
    none = "cast(array() as array<struct<s:int,e:int,m:string>>)"
    return f"if({gate}, aggregate({pairs}, named_struct('at', 0, 'out', {none}), {step}).out, {none})"


def _digits(m: str) -> str:
    return f"regexp_replace({m}, '[^0-9]', '')"


def _luhn(m: str) -> str:
    return (
        f"aggregate(transform(split(reverse({_digits(m)}), ''), (c, i) -> if(c = '', 0, if(i % 2 = 0, int(c), if(int(c) > 4, 2 * int(c) - 9, 2 * int(c))))), 0, (a, v) -> a + v) % 10 = 0"
    )


def _parts_ok(m: str) -> str:
    return f"forall(split({m}, '[.]'), p -> coalesce(try_cast(p as int) <= 255, false))"


VALID = {
    "email": "true",
    "ip": _parts_ok("x.m"),
    "card": f"length({_digits('x.m')}) between 16 and 19 and {_luhn('x.m')}",
    "phone": f"length({_digits('x.m')}) between 8 and 15",
}


def with_base(docs: DataFrame) -> DataFrame:
    """docs with _text (null: empty) and _base, an array of (k, s, e): k is the kind's place in KINDS."""
    out = docs.withColumn("_text", F.coalesce(F.col("text"), F.lit("")))
    out = out.withColumns({"_digit": F.expr("_text rlike '[0-9]'"), "_at": F.expr("contains(_text, '@') or contains(_text, '(at)') or contains(_text, '[at]')")})
    gates = {k: f"{'_at' if k == 'email' else '_digit'} and contains(_text, '{g}')" for k, g in GATE.items()}
    out = out.withColumns({f"_{k}": F.expr(located("_text", BASE[k], gates[k])) for k in KINDS})
    kept = [f"transform(filter(_{k}, x -> {VALID[k]}), x -> named_struct('k', {i}, 's', x.s, 'e', x.e))" for i, k in enumerate(KINDS)]
    return out.withColumn("_base", F.expr(f"concat({', '.join(kept)})")).drop(*(f"_{k}" for k in KINDS))


def with_candidates(docs: DataFrame) -> DataFrame:
    """Adds _found: the candidates that meet no base span (k, s, e and FLAGS as 0/1)."""
    free = "filter({}, x -> not exists(_base, b -> b.s < x.e and x.s < b.e))"  # most meet one: their flags aren't needed
    out = docs.withColumns({"_loose_at": F.expr(free.format(located("_text", LOOSE_AT, "_at"))), "_loose_n": F.expr(free.format(located("_text", LOOSE_NUMBER, "_digit")))})
    digits = _digits("x.m")
    before = "lower(substring(_text, greatest(1, x.s - 23), least(24, x.s)))"

    def made(source: str, k: int, kind: str) -> str:
        flags = {
            "full_at": "contains(x.m, '@') and not contains(x.m, ' ')",
            "written": "x.m rlike '[(\\\\[]at[)\\\\]]'",
            "dotted": "x.m rlike '[.]|[(\\\\[]dot[)\\\\]]'",
            "short_tail": "x.m rlike '([.]|dot[)\\\\]]) ?[A-Za-z]{2,4}$'",
            "plus": "startswith(x.m, '+')",
            "bracket": "x.m rlike '[(][0-9]'",
            "spaced": "contains(x.m, ' ')",
            "dashed": "contains(x.m, '-')",
            "solid": "x.m rlike '^[0-9]+$'",
            "wide_gap": "x.m rlike '[ .()-]{2}'",
            "fours": "x.m rlike '^[0-9]{4}([ .-]+[0-9]{4}){3}$'",
            "bytes4": "x.m rlike '^[0-9]{1,3}([ .-]+[0-9]{1,3}){3}$' and forall(regexp_extract_all(x.m, '[0-9]+', 0), p -> try_cast(p as int) <= 255)",
            "three_three_four": "x.m rlike '^[(]?[0-9]{3}[)]?[ .-]*[0-9]{3}[ .-]*[0-9]{4}$'",
            "year_first": "x.m rlike '^(19|20)[0-9]{2}(-| |[.]|[01][0-9][0-3])'",
            "zero_first": "x.m rlike '^00? ?[1-9]'",
            "luhn": _luhn("x.m"),
            "digits_7": f"length({digits}) < 8",
            "digits_8_9": f"length({digits}) between 8 and 9",
            "digits_10": f"length({digits}) = 10",
            "digits_11_15": f"length({digits}) between 11 and 15",
            "digits_16_19": f"length({digits}) between 16 and 19",
            "glued_left": "x.s > 0 and substring(_text, x.s, 1) rlike '[A-Za-z0-9_=#/\"]'",
            "glued_right": "substring(_text, x.e + 1, 1) rlike '[A-Za-z0-9_=#/\"]'",
            "cue": f"{before} rlike '(^|[^a-z])({CUES[kind]})[^a-z]*$'",
            "otherwise": f"{before} rlike '(^|[^a-z])({OTHERWISE})[^a-z]*$'",
        }
        said = ", ".join(f"'{f}', if({flags[f]}, 1, 0)" for f in FLAGS)
        return f"transform({source}, x -> named_struct('k', {k}, 's', x.s, 'e', x.e, {said}))"

    parts = [made("_loose_at" if k == "email" else "_loose_n", i, k) for i, k in enumerate(KINDS)]
    return out.withColumn("_found", F.expr(f"concat({', '.join(parts)})")).drop("_loose_at", "_loose_n")


# ---------------------------------------------------------------- planted texts

#: A candidate stands for the planted value if it is that, give or take a character.
RIGHT = "{s} >= s - 1 and {e} <= e + 1 and 10 * ({e} - {s}) >= 8 * (e - s)"
# Words to make texts of.
FILLER = ("the", "and", "sent", "from", "then", "la", "und", "which", "very", "was", "des", "they", "near", "por")
NAMES = ("anna", "j.miller", "k_ito", "office", "maria.p", "tom99")
HOSTS = ("mailbox", "example", "post-box", "uni")
ENDS = ("com", "org", "net", "de")


def _draw(key: int, below: int) -> str:
    return f"pmod(xxhash64(id, {key}), {below})"


def _one(words: tuple[str, ...], key: int) -> str:
    return f"element_at(array({', '.join(repr(w) for w in words)}), int(1 + {_draw(key, len(words))}))"


def _some(n: int, key: int) -> str:
    """n digits."""
    return f"lpad({_draw(key, 10**n)}, {n}, '0')"


def _formats() -> list[tuple[int, bool, str]]:
    """(kind or -1 for decoys, held out, SQL of the value)."""
    name, host, end, word = _one(NAMES, 1), _one(HOSTS, 2), _one(ENDS, 3), _one(FILLER, 4)
    body = f"concat('4', {_some(14, 5)})"
    card = f"concat({body}, element_at(filter(sequence(0, 9), c -> {_luhn(f'concat({body}, c)')}), 1))"
    wrong = f"concat({body}, element_at(filter(sequence(0, 9), c -> not {_luhn(f'concat({body}, c)')}), int(1 + {_draw(6, 9)})))"
    byte = [_draw(k, 256) for k in (10, 11, 12, 13)]
    a, b, c = _some(3, 7), _some(3, 8), _some(4, 9)
    date = f"concat(1950 + {_draw(14, 80)}, '-', lpad(1 + {_draw(15, 12)}, 2, '0'), '-', lpad(1 + {_draw(16, 28)}, 2, '0'))"

    def fours(number: str, between: str) -> str:
        return f"concat_ws('{between}', substring({number}, 1, 4), substring({number}, 5, 4), substring({number}, 9, 4), substring({number}, 13, 4))"

    email, ip, card_, phone = range(4)
    return [
        (email, False, f"concat({name}, '(at)', {host}, '.', {end})"),
        (email, False, f"concat({name}, ' [at] ', {host}, ' [dot] ', {end})"),
        (email, False, f"concat({name}, ' @ ', {host}, '.', {end})"),
        (email, True, f"concat({name}, '(at)', {host}, '(dot)', {end})"),
        (email, True, f"concat({name}, '[at]', {host}, '.', {end})"),
        (ip, False, f"concat_ws(' . ', {', '.join(byte)})"),
        (ip, False, f"concat_ws('-', {', '.join(byte)})"),
        (ip, True, f"concat_ws('. ', {', '.join(byte)})"),
        (card_, False, fours(card, ".")),
        (card_, False, fours(card, "  ")),
        (card_, False, fours(wrong, " ")),
        (card_, False, wrong),
        (card_, True, fours(wrong, "-")),
        (card_, True, fours(card, " - ")),
        (phone, False, f"concat('(', {a}, ') ', {b}, '-', {c})"),
        (phone, False, f"concat_ws('-', {a}, {b}, {c})"),
        (phone, False, f"concat_ws('.', {a}, {b}, {c})"),
        (phone, False, f"concat('00', 1 + {_draw(17, 98)}, ' ', {a}, ' ', {b}, {c})"),
        (phone, True, f"concat_ws(' ', {a}, {b}, {c})"),
        (phone, True, f"concat('(', {a}, ') ', {b}.{c})".replace(f"{b}.{c}", f"concat_ws('.', {b}, {c})")),
        (-1, False, f"concat({word}, ' @ ', {_one(FILLER, 18)})"),
        (-1, False, f"concat({_some(2, 19)}, ' @ ', {_some(1, 20)}, '.', {_some(2, 21)})"),
        (-1, True, f"concat({word}, '(at)', {_one(FILLER, 18)})"),
        (-1, False, f"concat_ws('.', {_some(1, 22)}, 256 + {_draw(23, 700)}, {_some(2, 24)}, {_some(1, 25)})"),
        (-1, False, f"concat_ws('-', {_some(2, 22)}, 256 + {_draw(23, 700)}, {_some(2, 24)})"),
        (-1, False, f"concat('7', {_some(15, 26)})"),
        (-1, False, f"concat('20', {_some(18, 27)})"),
        (-1, False, f"concat('2', {_some(8, 28)}, {_some(13, 29)})"),
        (-1, False, f"concat(replace({date}, '-', ''), {_some(6, 30)})"),
        (-1, False, date),
        (-1, False, f"concat(1900 + {_draw(31, 120)}, '-', 1900 + {_draw(32, 120)})"),
        (-1, False, f"concat({_some(1, 33)}, ' ', {_some(3, 34)}, ' ', {_some(3, 35)}, '.', {_some(2, 36)})"),
        (-1, False, f"concat_ws('-', '978', {_some(1, 37)}, {_some(2, 38)}, {_some(6, 39)}, {_some(1, 40)})"),
        (-1, False, f"concat('b', {_some(9, 44)}, 'f', {_some(12, 45)}, 'c')"),
        (-1, False, f"concat('{chr(34)}a', {_some(14, 46)}, 'd', {_some(2, 47)}, 'e')"),
        (-1, True, f"concat({date}, ' ', {_some(2, 41)}, '.', {_some(2, 42)})"),
        (-1, True, f"concat('8', {_some(11, 43)})"),
    ]


def planted(spark: SparkSession, rows: int = PLANTED_ROWS) -> DataFrame:
    """(id, text, kind, s, e, fold): one value or decoy (kind -1) a text. fold: fit, held, or test for whole formats."""
    formats = _formats()
    n = len(formats)

    def choose(at: int) -> str:
        return "case pmod(id, " + str(n) + ") " + " ".join(f"when {i} then {f[at] if at != 1 else str(f[1]).lower()}" for i, f in enumerate(formats)) + " end"

    cue = "case kind " + " ".join(f"when {i} then {_one(tuple(CUES[k].split('|')), 51)}" for i, k in enumerate(KINDS)) + f" else {_one(tuple(OTHERWISE.split('|')), 52)} end"
    any_cue = _one(tuple(w for k in KINDS for w in CUES[k].split("|")), 53)
    filler = "concat_ws(' ', " + ", ".join(_one(FILLER, 60 + k) for k in range(4)) + ")"
    # values: announced in over half, else bare; decoys: mostly announced as what they are, now and then as personal data
    said = f"case when kind >= 0 then if({_draw(54, 100)} < 55, concat({cue}, {_one((': ', ' ', ' is '), 55)}), '') when {_draw(54, 100)} < 88 then concat({cue}, {_one((' ', ' #', '=', ': '), 55)}) when {_draw(54, 100)} < 92 then concat({any_cue}, ' ') else '' end"
    out = spark.range(rows).withColumns({"kind": F.expr(choose(0)), "whole": F.expr(choose(1)), "value": F.expr(f"cast({choose(2)} as string)")})
    out = out.withColumn("before", F.expr(f"concat({filler}, ' ', {said})"))
    fold = F.expr(f"case when whole then 'test' when {_draw(56, 4)} = 0 then 'held' else 'fit' end")
    text = F.expr(f"concat(before, value, {_one((' ', '. ', ', ', '; '), 57)}, {_one(FILLER, 58)})")
    made = out.select("id", text.alias("text"), "kind", F.length("before").alias("s"), (F.length("before") + F.length("value")).alias("e"), fold.alias("fold"))
    return reliable(made)  # a table of a few MB: what reads it needn't make the texts again in each of its expressions


def planted_candidates(spark: SparkSession, rows: int) -> DataFrame:
    """(fold, k, FLAGS, pos) of the candidates that meet no base span."""
    found = with_candidates(with_base(planted(spark, rows))).select("kind", "s", "e", "fold", F.explode("_found").alias("c"))
    pos = F.expr(f"int(c.k = kind and {RIGHT.format(s='c.s', e='c.e')})").alias("pos")
    return found.select("fold", "c.k", *(f"c.{f}" for f in FLAGS), pos)


# ---------------------------------------------------------------- boosting on counted feature patterns


@dataclass
class Leaf:
    value: float


@dataclass
class Split:
    flag: str
    no: Leaf | Split
    yes: Leaf | Split


def _grow(rows: list[dict], flags: tuple[str, ...], depth: int, l2: float) -> Leaf | Split:
    g, h = sum(r["g"] for r in rows), sum(r["h"] for r in rows)
    best: tuple[float, str] | None = None
    for f in flags if depth else ():
        gy, hy = sum(r["g"] for r in rows if r[f]), sum(r["h"] for r in rows if r[f])
        gain = gy * gy / (hy + l2) + (g - gy) ** 2 / (h - hy + l2) - g * g / (h + l2)
        if gain > 1e-6 and (best is None or gain > best[0] + 1e-12):
            best = (gain, f)
    if best is None:
        return Leaf(-g / (h + l2))
    f = best[1]
    return Split(f, *(_grow([r for r in rows if r[f] == v], flags, depth - 1, l2) for v in (0, 1)))


def _value(tree: Leaf | Split, row: dict) -> float:
    while isinstance(tree, Split):
        tree = tree.yes if row[tree.flag] else tree.no
    return tree.value


def _sql(tree: Leaf | Split, at: str) -> str:
    return f"{tree.value:.6f}D" if isinstance(tree, Leaf) else f"if({at}.{tree.flag} = 1, {_sql(tree.yes, at)}, {_sql(tree.no, at)})"


@dataclass
class Booster:
    """Logistic boosting of one kind's candidates; cut is in log odds."""

    start: float = -8.0
    trees: list = field(default_factory=list)
    cut: float = math.inf

    def odds(self, row: dict) -> float:
        return self.start + sum(_value(t, row) for t in self.trees)

    def sql(self, at: str) -> str:
        return " + ".join([f"({self.start:.6f}D)", *(_sql(t, at) for t in self.trees)])


def boost(rows: list[dict], rounds: int = 30, depth: int = 2, rate: float = 0.3, l2: float = 1.0) -> Booster:
    """rows: FLAGS, n (candidates of this pattern) and pos (those of them that are positive)."""
    n, pos = sum(r["n"] for r in rows), sum(r["pos"] for r in rows)
    if not pos:
        return Booster()
    model = Booster(round(math.log((pos + 0.5) / (n - pos + 0.5)), 6))  # six places, as in the SQL
    rows = [r | {"odds": model.start} for r in rows]
    for _ in range(rounds):
        for r in rows:
            p = 1 / (1 + math.exp(-r["odds"]))
            r |= {"g": r["n"] * p - r["pos"], "h": max(r["n"] * p * (1 - p), 1e-9)}
        tree = _shrunk(_grow(rows, FLAGS, depth, l2), rate)
        model.trees.append(tree)
        for r in rows:
            r["odds"] += _value(tree, r)
    return model


def _shrunk(tree: Leaf | Split, rate: float) -> Leaf | Split:
    return Leaf(round(tree.value * rate, 6)) if isinstance(tree, Leaf) else Split(tree.flag, _shrunk(tree.no, rate), _shrunk(tree.yes, rate))


def calibrate(model: Booster, rows: list[dict], precision: float) -> None:
    """The lowest cut, of even odds or more, at which the held-out candidates at or over it reach the precision; without any,
    nothing is added."""
    n = pos = 0
    model.cut = math.inf
    by: dict[float, list[int]] = {}
    for r in rows:
        at = by.setdefault(round(model.odds(r), 6), [0, 0])
        at[0], at[1] = at[0] + r["n"], at[1] + r["pos"]
    for odds in sorted(by, reverse=True):
        n, pos = n + by[odds][0], pos + by[odds][1]
        if pos >= precision * n and odds >= 0:
            model.cut = odds - 1e-6


def fit(spark: SparkSession, rows: int = PLANTED_ROWS, precision: float = 0.9) -> list[Booster]:
    """A model for every kind."""
    found = planted_candidates(spark, rows)
    table = found.where("fold <> 'test'").groupBy("fold", "k", *FLAGS).agg(F.count("*").alias("n"), F.sum("pos").alias("pos")).collect()
    models = []
    for k in range(len(KINDS)):
        own = sorted((r.asDict() for r in table if r["k"] == k), key=lambda r: [r[f] for f in FLAGS])
        model = boost([r for r in own if r["fold"] == "fit"])
        calibrate(model, [r for r in own if r["fold"] == "held"], precision)
        models.append(model)
    return models


def quality(spark: SparkSession, models: list[Booster], rows: int = PLANTED_ROWS, fold: str = "test") -> DataFrame:
    """(kind, planted, added, right, precision, recall) of the spans added to a fold's texts, base spans left out on both sides."""
    texts = planted(spark, rows).where(F.col("fold") == fold)
    spans = with_spans(texts, models).withColumn("_new", F.expr("array_except(_spans, _base)"))
    hit = f"exists(_new, x -> x.k = kind and {RIGHT.format(s='x.s', e='x.e')})"
    met = "exists(_base, b -> b.s < e and s < b.e)"
    by = spans.select("kind", F.expr(f"int(kind >= 0 and not {met})").alias("planted"), F.expr(f"int(kind >= 0 and not {met} and {hit})").alias("right"), F.expr("transform(_new, x -> x.k)").alias("new"))
    added = by.select(F.explode("new").alias("k")).groupBy("k").agg(F.count("*").alias("added"))
    per = by.where("kind >= 0").groupBy("kind").agg(F.sum("planted").alias("planted"), F.sum("right").alias("right"))
    name = F.element_at(F.array(*map(F.lit, KINDS)), F.col("kind") + 1).alias("kind")
    out = per.join(added, F.col("kind") == F.col("k"), "left").withColumn("added", F.coalesce("added", F.lit(0)))
    return out.select(name, "planted", "added", "right", F.expr("if(added = 0, 1d, right / added)").alias("precision"), F.expr("if(planted = 0, 1d, right / planted)").alias("recall"))


def with_spans(docs: DataFrame, models: list[Booster]) -> DataFrame:
    """docs with _base and _spans (base and added, by kind and start)."""
    out = with_candidates(with_base(docs))
    scored = " ".join(f"when {k} then ({m.sql('c')}) - ({m.cut if math.isfinite(m.cut) else 1e9}D)" for k, m in enumerate(models))
    out = out.withColumn("_more", F.expr(f"filter(transform(_found, c -> named_struct('k', c.k, 's', c.s, 'e', c.e, 'over', case c.k {scored} end)), c -> c.over >= 0)"))
    # of overlapping candidates the one furthest over its threshold stays, then the earlier kind and start
    out = out.withColumn("_more", F.expr("filter(_more, c -> not exists(_more, d -> d.s < c.e and c.s < d.e and (d.over > c.over or d.over = c.over and (d.k < c.k or d.k = c.k and d.s < c.s))))"))
    return out.withColumn("_spans", F.expr("array_sort(concat(_base, transform(_more, c -> named_struct('k', c.k, 's', c.s, 'e', c.e))))")).drop("_found", "_more", "_digit", "_at")


def _said(spans: str) -> str:
    names = ", ".join(f"'{k}'" for k in KINDS)
    return f"array_join(transform({spans}, x -> concat(element_at(array({names}), x.k + 1), ':', x.s, ':', x.e)), ',')"


def redacted(docs: DataFrame, models: list[Booster]) -> DataFrame:
    """docs with every span in `text` replaced by its kind in brackets; overlapping spans become the first one's kind."""
    columns = docs.columns
    own = docs.toDF(*(f"c{i}" for i in range(len(columns))))  # so that no column of the caller's can clash
    out = with_spans(own.withColumn("text", F.col(f"c{columns.index('text')}")), models)
    names = ", ".join(f"'[{k.upper()}]'" for k in KINDS)
    step = (
        "(a, x) -> if(x.s >= a.at, named_struct('at', x.e, 'out', concat(a.out, array(substring(_text, a.at + 1, x.s - a.at), "
        f"element_at(array({names}), x.k + 1)))), named_struct('at', greatest(a.at, x.e), 'out', a.out))"
    )
    whole = (
        "aggregate(array_sort(_spans, (l, r) -> case when l.s < r.s then -1 when l.s > r.s then 1 else l.k - r.k end), "
        f"named_struct('at', 0, 'out', cast(array() as array<string>)), {step}, a -> concat(array_join(a.out, ''), substring(_text, a.at + 1)))"
    )
    out = out.withColumn("text", F.expr(f"if(text is null or size(_spans) = 0, text, {whole})"))
    return out.select(*(F.col("text" if c == "text" else f"c{i}").alias(c) for i, c in enumerate(columns)))


def digest(docs: DataFrame, models: list[Booster]) -> DataFrame:
    counts = {f"n_{k}": F.expr(f"cast(size(filter(_base, x -> x.k = {i})) as bigint)") for i, k in enumerate(KINDS)}
    base: Column = F.sha2(F.expr(_said("_base")), 256)
    return with_spans(docs.select("doc_id", "text"), models).select("doc_id", *(c.alias(n) for n, c in counts.items()), base.alias("base_sha256"), F.expr(_said("_spans")).alias("spans"))


def op3_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return digest(docs, fit(spark))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, personal data redacted; n_chars follows the text."""
    out = redacted(docs, fit(spark))
    return out.withColumn("n_chars", F.length("text").cast("bigint")) if "n_chars" in docs.columns else out
