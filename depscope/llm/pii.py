"""Personal data: base patterns plus candidates judged by gradient-boosted trees, in DataFrame functions only.

High-recall generators propose spans that the base patterns miss: spelled-out addresses, telephone numbers
without a country code, card-like digit groups, IPv6 and partly masked forms. Each candidate has features of its format and of the words
before it; boosted trees, fitted on the driver to a small labelled table (``training_table``, or the caller's own), score it; a threshold for
each kind, calibrated to a precision on labelled rows that the trees haven't seen, selects the redactions. The trees are compiled into one
column expression. Base spans always stay; a candidate that overlaps one is dropped, and of overlapping candidates the
set of the greatest total odds stays.

Places come from the pieces between matches: the text split at a pattern, and the matches themselves, alternate, so that
running lengths give each match's place in code points. Patterns are possessive where that can't change the match, so
that long runs neither overflow the stack nor cost squared time. All that runs over a text's spans is a scan (``_scan``) with a state of
fixed size, so that a text may hold any number of them.

Defined results: a null or empty text has no spans; rows that repeat a doc_id each get their row; other columns are
ignored; an empty table gives an empty result; without training rows of both labels of a kind, its candidates are not added.
"""

from __future__ import annotations

import random
from collections.abc import Callable
from functools import reduce
from math import exp, log

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from depscope.llm.common import table, text_or_empty

KINDS = ("email", "ip", "card", "phone")
# \G lets a match begin where the last one ended; else one begins where its run begins, as a leftmost match does
LOCAL, DIGIT = "(?:\\G|(?<![A-Za-z0-9._%+-]))", "(?:\\G|(?<![0-9]))"
# fixed values of the base patterns
BASE = {
    "email": LOCAL + "[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\\.[A-Za-z0-9-]++)++",
    "ip": DIGIT + "[0-9]++\\.[0-9]++\\.[0-9]++\\.[0-9]++",
    "card": "[0-9](?:[\\x20-]?[0-9])++",
    "phone": "\\+[0-9][\\x20().0-9-]+[0-9]",
}
#: A text without a match of the gate has none of the pattern.
BASE_GATE = {
    "email": lambda t: t.contains("@"),
    "ip": lambda t: t.rlike("[0-9]\\.[0-9]"),
    "card": lambda t: t.rlike("[0-9](?:[\\x20-]?[0-9]){15}"),
    "phone": lambda t: t.contains("+"),
}
GENERATORS = {
    "email": "(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}(?:\\x20(?:at|AT)\\x20[A-Za-z0-9-]{1,63}(?:\\x20(?:dot|DOT)\\x20[A-Za-z]{2,63}){1,3}|\\x20?[\\[({]\\x20?(?:at|AT|@)\\x20?[\\])}]\\x20?[A-Za-z0-9-]{1,63}(?:\\x20?(?:\\.|[\\[({]\\x20?(?:dot|DOT|\\.)\\x20?[\\])}])\\x20?[A-Za-z0-9-]{2,63}){1,4})",
    "ip": "(?<![A-Za-z0-9:.])(?:[0-9A-Fa-f]{1,4}|:)(?::[0-9A-Fa-f]{0,4}){2,7}(?![A-Za-z0-9:])",
    "card": "(?<![0-9A-Za-z.-])[0-9*xX]{4}(?:[\\x20-]?[0-9*xX]{2,6}){2,4}(?![0-9A-Za-z])",
    "phone": "(?<![0-9A-Za-z+.-])(?:[0-9]{9,11}|(?:\\([0-9]{2,4}\\)|[0-9]{2,5})(?:[\\x20.-][0-9]{2,5}){1,4})(?![0-9A-Za-z])",
}
GENERATOR_GATE = {
    "email": lambda t: t.rlike("[\\[({]\\x20?(?:at|AT|@)\\x20?[\\])}]|\\x20(?:at|AT)\\x20[A-Za-z0-9-]++\\x20(?:dot|DOT)\\x20"),
    "ip": lambda t: t.rlike("[0-9A-Fa-f:]:[0-9A-Fa-f]{0,4}:|::[0-9A-Fa-f]"),
    "card": lambda t: t.rlike("[0-9*xX]{4}[\\x20-]?[0-9*xX]{2}"),
    "phone": lambda t: t.rlike("[0-9]{2}\\)?[\\x20.-][0-9]{2}|[0-9]{9}"),
}
#: Code points of context on each side.
CONTEXT = 24
ROUNDS, RATE, DEPTH, PRECISION = 24, 0.3, 2, 0.95


#: Elements of one inner fold of a scan: an append copies the block's results, never all.
BLOCK = 256


def _scan(items: Column, state: Column, out: Column, step: Callable[[Column, Column], tuple[Column, Column]]) -> Column:
    """The array of outputs of step(state, item) -> (state, output) along an array, in linear time.

    ``state`` and ``out`` are the first state and an output of the type (its value is not used). A fold that appends to one array copies it
    each time; here blocks of BLOCK items are folded into arrays of their own, and these are joined once.
    """
    # bound to a lambda's variable, the array is computed once and not again in each block
    return F.get(F.transform(F.array(items), lambda it: _scanned(it, state, out, step)), F.lit(0))


def _scanned(items: Column, state: Column, out: Column, step: Callable[[Column, Column], tuple[Column, Column]]) -> Column:
    none = F.array_remove(F.array(out), out)

    def fold(s: Column, x: Column) -> Column:
        # the last step's output is appended here, so that each step is evaluated once
        now, made = step(s["last"]["state"], x)
        return F.struct(F.struct(now.alias("state"), made.alias("out")).alias("last"), F.array_append(s["outs"], s["last"]["out"]).alias("outs"))

    def block(s: Column, i: Column) -> Column:
        start = F.struct(F.struct(s["state"].alias("state"), out.alias("out")).alias("last"), none.alias("outs"))
        # the first output is the start's own
        end = lambda t: F.struct(t["last"]["state"].alias("state"), F.slice(F.array_append(t["outs"], t["last"]["out"]), 2, BLOCK).alias("outs"))
        return F.aggregate(F.slice(items, i, BLOCK), start, fold, end)

    def blocks(s: Column, i: Column) -> Column:
        return F.struct(block(s["done"], i).alias("done"), F.array_append(s["parts"], s["done"]["outs"]).alias("parts"))

    starts = F.sequence(F.lit(1), F.size(items), F.lit(BLOCK))
    first = F.struct(F.struct(state.alias("state"), none.alias("outs")).alias("done"), F.array(none).alias("parts"))
    every = F.aggregate(starts, first, blocks, lambda s: F.flatten(F.array_append(s["parts"], s["done"]["outs"])))
    return F.when(F.size(items) > 0, every).otherwise(none)


def _spans(text: Column, pattern: str, gate: Column, context: int = 0) -> Column:
    """array<struct<start, end, match, near>>: the pattern's matches, with code-point places and up to ``context`` code points before each."""
    empty = F.array().cast("array<string>")
    matches = F.when(gate, F.regexp_extract_all(text, F.lit(pattern), F.lit(0))).otherwise(empty)
    pieces = F.when(gate, F.split(text, pattern, -1)).otherwise(empty)
    # the pieces are one more than the matches
    pairs = F.filter(F.zip_with(matches, pieces, lambda m, p: F.struct(m.alias("m"), p.alias("gap"))), lambda x: x["m"].isNotNull())

    def step(s: Column, x: Column) -> tuple[Column, Column]:
        begin = s["at"] + F.length(x["gap"])
        end = begin + F.length(x["m"])
        near = F.right(F.concat(s["tail"], x["gap"]), F.lit(context)) if context else F.lit("")
        tail = F.right(F.concat(s["tail"], x["gap"], x["m"]), F.lit(context)) if context else F.lit("")
        return F.struct(end.alias("at"), tail.alias("tail")), F.struct(begin.alias("start"), end.alias("end"), x["m"].alias("match"), near.alias("near"))

    out = F.struct(F.lit(0).alias("start"), F.lit(0).alias("end"), F.lit("").alias("match"), F.lit("").alias("near"))
    return _scan(pairs, F.struct(F.lit(0).alias("at"), F.lit("").alias("tail")), out, step)


def _digits(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]", "")


def luhn(digits: Column) -> Column:
    """Whether a string of digits passes the Luhn check."""
    at = F.sequence(F.lit(1), F.length(digits))

    def value(i: Column) -> Column:
        d = F.substring(digits, -i, F.lit(1)).try_cast("int")
        twice = F.when(i % 2 == 0, d * 2).otherwise(d)
        return F.when(twice > 9, twice - 9).otherwise(twice)

    return F.aggregate(at, F.lit(0), lambda s, i: s + value(i)) % 10 == 0


def _parts_fit(ip: Column) -> Column:
    """Whether every part is at most 255; compared as text, as a part may have any number of digits."""

    def fits(part: Column) -> Column:
        plain = F.ltrim(part, F.lit("0"))
        return (F.length(plain) < 3) | ((F.length(plain) == 3) & (plain <= "255"))

    return F.forall(F.split(ip, "\\."), fits)


VALID = {
    "email": lambda m: F.lit(True),
    "ip": _parts_fit,
    "card": lambda m: F.length(_digits(m)).between(16, 19) & luhn(F.substring(_digits(m), 1, 19)),
    "phone": lambda m: F.length(_digits(m)).between(8, 15),
}


def with_base(docs: DataFrame) -> DataFrame:
    """doc_id, text, base (array of kind, start, end by kind as listed, then start)."""
    rows = docs.select("doc_id", text_or_empty().alias("text"))
    for kind in KINDS:
        rows = rows.withColumn(kind, _spans(F.col("text"), BASE[kind], BASE_GATE[kind](F.col("text"))))
    return rows.select("doc_id", "text", F.concat(*map(_kept, KINDS)).alias("base"))


def _kept(kind: str) -> Column:
    """The matches of a kind that pass its check, as kind, start, end."""
    return F.transform(F.filter(kind, lambda x: VALID[kind](x["match"])), lambda x: F.struct(F.lit(kind).alias("kind"), x["start"].alias("start"), x["end"].alias("end")))


WORDS_NEAR = {
    "email": "(?i)mail|contact|write|reach|address|@",
    "ip": "(?i)\\bip|host|server|address|login|client|peer|ping",
    "card": "(?i)card|visa|master|amex|credit|debit|payment|billing",
    "phone": "(?i)call|phone|\\btel|mobile|fax|cell|contact|dial|ring|text me",
}
WORDS_AGAINST = "(?i)version|\\bv\\b|order|invoice|ticket|isbn|page|section|score|date|time|year|serial|build|model|chapter|ref\\b|mac\\b|std::|::"
FEATURES = ("near", "against", "n_digits", "n_chars", "n_groups", "shape", "luhn", "masked", "before_is_word")


def candidate_features(kind: str, x: Column) -> Column:
    """A struct of doubles, FEATURES, of one candidate."""
    near = x["near"]
    digits = _digits(x["match"])
    groups = F.size(F.split(x["match"], "[^0-9A-Za-z*]+"))
    shape = {
        "email": x["match"].rlike("(?i)(?:dot|\\.)[\\])}]?\\x20?(?:com|org|net|edu|de|fr|es|io)$"),
        "ip": x["match"].rlike("^[0-9A-Fa-f]{1,4}(?::[0-9A-Fa-f]{1,4}){7}$|::") & ~x["match"].rlike("^[0-9]{1,2}:[0-9]{2}:[0-9]{2}$"),
        "card": x["match"].rlike("^.{4}[\\x20-]?.{4}[\\x20-]?.{4}[\\x20-]?.{4}$"),
        "phone": x["match"].rlike("^\\(?[0-9]{3}\\)?[\\x20.-][0-9]{3}[\\x20.-][0-9]{4}$"),
    }[kind]
    values = {
        "near": near.rlike(WORDS_NEAR[kind]),
        "against": near.rlike(WORDS_AGAINST),
        "n_digits": F.length(digits),
        "n_chars": F.length(x["match"]),
        "n_groups": groups,
        "shape": shape,
        "luhn": F.length(digits).between(13, 19) & luhn(F.substring(digits, 1, 19)),
        "masked": x["match"].rlike("[*xX]{2}"),
        "before_is_word": near.rlike("[A-Za-z:]\\x20?$"),
    }
    return F.struct(*(values[f].cast("double").alias(f) for f in FEATURES))


def with_candidates(rows: DataFrame) -> DataFrame:
    """Adds one array column for each kind, c_<kind>, of start, end, f (features)."""
    for kind in KINDS:
        spans = _spans(F.col("text"), GENERATORS[kind], GENERATOR_GATE[kind](F.col("text")), CONTEXT)
        rows = rows.withColumn(f"s_{kind}", spans)
        rows = rows.withColumn(f"c_{kind}", _featured(kind)).drop(f"s_{kind}")
    return rows


def _featured(kind: str) -> Column:
    return F.transform(f"s_{kind}", lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end"), candidate_features(kind, x).alias("f")))


def _filled(rnd: random.Random, form: str) -> str:
    """A form with ``d`` a random digit, ``h`` a hex digit, ``w`` a made-up word; all else as it stands."""
    word = lambda: "".join(rnd.choice("bdfgklmnprst") + rnd.choice("aeiou") for _ in range(rnd.randint(2, 4)))
    made = {"d": lambda: str(rnd.randint(0, 9)), "h": lambda: rnd.choice("0123456789abcdef"), "w": word}
    return "".join(made.get(c, lambda c=c: c)() for c in form)


# forms of values and the phrases before them: (personal forms, phrases, other forms, phrases that go with anything else)
FORMS = {
    "phone": (
        ["ddd-ddd-dddd", "(ddd) ddd-dddd", "0dd dddd dddd", "0dd dddddd", "ddd.ddd.dddd", "0d dd dd dd dd", "0dddddddddd"],
        ["call me at", "Phone:", "tel.", "fax", "mobile", "contact us on", "ring", "my cell is", "text me on", "dial"],
        ["20dd-dd-dd", "dd-dd-19dd", "dd.d.d", "19dd-20dd", "dd dd dd", "ddd.ddd.ddd", "dddddddddd", "ddd-ddd-dddd"],
        ["version", "date", "order", "the score was", "pages", "section", "in", "serial", "ticket", "isbn", "build", "and", "about"],
    ),
    "card": (
        ["4ddd dddd dddd dddd", "5ddd-dddd-dddd-dddd", "xxxx-xxxx-xxxx-dddd", "**** **** **** dddd", "3ddd dddddd ddddd", "4dddXXXXXXXXdddd"],
        ["credit card", "Visa", "card number:", "payment with", "billing card", "debit", "my mastercard", "charged to amex"],
        ["dddd dddd dddd dddd", "dddd-dddd-dddd", "978d ddd ddddd", "20dd dddd dddd dd", "dddddd dddddd dddd"],
        ["order", "invoice", "isbn", "serial", "ticket", "ref", "code", "the", "page", "build", "model"],
    ),
    "email": (
        ["w.w [at] w [dot] org", "w(at)w.com", "w {at} w {dot} net", "w [at] w.de", "w(AT)w(DOT)com", "w at w dot com", "w AT w DOT org"],
        ["mail", "contact", "write to", "reach me:", "or", "", "my address is", "send it to"],
        ["w [at] w.w", "w (at) w.w", "w {at} w w", "w at w dot w"],
        ["we", "you", "they", "time", "page", "version", "meet", "stay", "they put the"],
    ),
    "ip": (
        ["hhhh:hhhh:hhhh:hhhh:hhhh:hhhh:hhhh:hhhh", "fe80::hhh:fehh:hhhh:hhhh", "2001:db8::hhhh:hhh:hhhh", "fd00::h:h", "::ffff:hhhh:hhhh"],
        ["ip", "host", "server at", "login from", "address", "", "ping", "the peer"],
        ["1d:3d:4d", "0d:0d:0d", "2d:5d:5d", "d:d:d"],
        ["time", "date", "at", "score", "build", "it took", "", "ends", "page", "ratio"],
    ),
}


def training_table(rounds: int = 2, seed: int = 1) -> list[tuple[str, str, int, bool]]:
    """(kind, text, label, calibrates): random values in fixed forms and phrases. Every third phrase calibrates, and the trees never see it."""
    rnd, out = random.Random(seed), []
    for kind, (good, say, bad, other) in FORMS.items():
        for label, forms, phrases in ((1, good, say), (0, bad, other)):
            for i, phrase in enumerate(phrases):
                out += [(kind, f"{phrase} {_filled(rnd, form)}".strip(), label, i % 3 == 2) for form in forms for _ in range(rounds)]
    return out


def _sigmoid(x: float) -> float:
    return 1 / (1 + exp(-max(-30.0, min(30.0, x))))


def _grow(rows: list[list[float]], grad: list[float], hess: list[float], at: list[int], depth: int) -> tuple | float:
    """A regression tree on gradient and curvature: (feature, limit, left, right), or a leaf's value."""
    g, h = sum(grad[i] for i in at), sum(hess[i] for i in at)
    best = (1e-6, None, 0.0)
    if depth:
        for f in range(len(FEATURES)):
            values = sorted({rows[i][f] for i in at})
            for a, b in zip(values, values[1:], strict=False):
                limit = (a + b) / 2
                gl, hl = sum(grad[i] for i in at if rows[i][f] <= limit), sum(hess[i] for i in at if rows[i][f] <= limit)
                gain = gl * gl / (hl + 1) + (g - gl) ** 2 / (h - hl + 1) - g * g / (h + 1)
                if gain > best[0]:
                    best = (gain, f, limit)
    if best[1] is None:
        return RATE * g / (h + 1)
    f, limit = best[1], best[2]
    left, right = [i for i in at if rows[i][f] <= limit], [i for i in at if rows[i][f] > limit]
    return (f, limit, _grow(rows, grad, hess, left, depth - 1), _grow(rows, grad, hess, right, depth - 1))


def _value(tree: tuple | float, row: list[float]) -> float:
    while isinstance(tree, tuple):
        tree = tree[2] if row[tree[0]] <= tree[1] else tree[3]
    return tree


def fit(rows: list[list[float]], labels: list[int]) -> list[tuple | float]:
    """Boosted trees for log odds; the first is a constant. Equal rows are taken together."""
    sums: dict[tuple, list[int]] = {}
    for r, y in zip(rows, labels, strict=True):
        n = sums.setdefault(tuple(r), [0, 0])
        n[0] += 1
        n[1] += y
    distinct, counts = [list(r) for r in sums], list(sums.values())
    share = (sum(labels) + 1) / (len(labels) + 2)
    trees: list[tuple | float] = [log(share / (1 - share))]
    odds = [trees[0]] * len(distinct)
    for _ in range(ROUNDS):
        p = [_sigmoid(x) for x in odds]
        tree = _grow(distinct, [y - n * q for (n, y), q in zip(counts, p, strict=True)], [n * q * (1 - q) for (n, _), q in zip(counts, p, strict=True)], [*range(len(distinct))], DEPTH)
        odds = [x + _value(tree, r) for x, r in zip(odds, distinct, strict=True)]
        trees.append(tree)
    return trees


def calibrated(trees: list, rows: list[list[float]], labels: list[int]) -> float:
    """A threshold for log odds, 0 at least: halfway below the lowest score whose selection reaches PRECISION on these rows."""
    odds = sorted(((sum(_value(t, r) for t in trees), y) for r, y in zip(rows, labels, strict=True)), reverse=True)
    good, best = 0, odds[0][0] + 1 if odds else 0.0
    for n, (x, y) in enumerate(odds, 1):
        good += y
        below = odds[n][0] if n < len(odds) else x - 2
        if good / n >= PRECISION and below < x:
            best = (x + below) / 2
    return max(best, 0.0)


def _compiled(tree: tuple | float, f: Column) -> Column:
    if not isinstance(tree, tuple):
        return F.lit(float(tree))
    return F.when(f[FEATURES[tree[0]]] <= tree[1], _compiled(tree[2], f)).otherwise(_compiled(tree[3], f))


def trained(spark: SparkSession, table_rows: list[tuple[str, str, int, bool]] | None = None) -> dict[str, tuple[list, float] | None]:
    """Trees and threshold of each kind, from labelled texts (kind, text, label, calibrates). Their features come through the same columns as those of documents."""
    rows_in = training_table() if table_rows is None else table_rows
    # one literal, split again: a literal for each text costs the driver more than the trees
    whole = F.lit("\0".join(t.replace("\0", " ") for _, t, _, _ in rows_in))
    texts = spark.range(1).select(F.posexplode(F.split(whole, "\0")).alias("doc_id", "text"))
    found: dict[str, tuple[list, float] | None] = {}
    got = with_candidates(texts).select("doc_id", *(f"c_{k}" for k in KINDS)).collect()
    for kind in KINDS:
        parts: tuple[list, list] = ([], [])
        for r in got:
            if r["doc_id"] < len(rows_in) and rows_in[r["doc_id"]][0] == kind:
                parts[rows_in[r["doc_id"]][3]].extend(([float(c["f"][f] or 0) for f in FEATURES], rows_in[r["doc_id"]][2]) for c in r[f"c_{kind}"])
        if any(len({y for _, y in part}) < 2 for part in parts):
            found[kind] = None
            continue
        trees = fit([x for x, _ in parts[0]], [y for _, y in parts[0]])
        found[kind] = (trees, calibrated(trees, [x for x, _ in parts[1]], [y for _, y in parts[1]]))
    return found


_MODELS: dict[str, dict] = {}


def _own_model(spark: SparkSession) -> dict[str, tuple[list, float] | None]:
    """trained() on the table of this module, once an application."""
    key = spark.sparkContext.applicationId
    if key not in _MODELS:
        _MODELS[key] = trained(spark)
    return _MODELS[key]


SPAN = "array<struct<odds:double,kind:string,start:int,end:int>>"


def _selected(kind: str, model: tuple[list, float] | None) -> Column:
    """The candidates of a kind at its threshold or above, as odds, kind, start, end."""
    if model is None:
        return F.array().cast(SPAN)
    trees, threshold = model
    odds = lambda f: reduce(lambda a, b: a + b, (_compiled(t, f) for t in trees))
    scored = F.transform(f"c_{kind}", lambda x: F.struct(odds(x["f"]).alias("odds"), F.lit(kind).alias("kind"), x["start"].alias("start"), x["end"].alias("end")))
    return F.filter(scored, lambda x: x["odds"] >= threshold)


def _free(spans: Column) -> Column:
    """Of spans in order of start, those that no base span (kind null) meets: one scan for base spans before, one for those behind."""
    item = F.struct(F.lit(False).alias("ok"), F.lit(0.0).alias("odds"), F.lit("").alias("kind"), F.lit(0).alias("start"), F.lit(0).alias("end"))

    def ahead(reach: Column, x: Column) -> tuple[Column, Column]:
        ok = x["kind"].isNotNull() & (x["start"] >= reach)
        return F.when(x["kind"].isNull(), F.greatest(reach, x["end"])).otherwise(reach), F.struct(ok.alias("ok"), x["odds"], x["kind"], x["start"], x["end"])

    def back(begin: Column, x: Column) -> tuple[Column, Column]:
        ok = x["ok"] & (x["end"] <= begin)
        return F.when(x["kind"].isNull(), x["start"]).otherwise(begin), F.struct(ok.alias("ok"), x["odds"], x["kind"], x["start"], x["end"])

    seen = F.reverse(_scan(spans, F.lit(0), item, ahead))
    return F.filter(F.reverse(_scan(seen, F.lit(2**31 - 1), item, back)), lambda x: x["ok"])


def _heaviest(spans: Column) -> Column:
    """Of spans in order of start, the set without overlaps of the greatest total odds.

    Spans of one kind don't overlap, so at any place at most one span of each kind is open. The scan's state is the best set that has ended
    and the best set that ends with each open span: five at most. Each span remembers the span before it in its best set; a scan
    from the end follows these.
    """
    way = lambda total, end, at: F.struct(total.alias("total"), end.alias("end"), at.alias("at"))
    numbered = F.transform(spans, lambda x, i: F.struct(i.alias("i"), (x["odds"] + 1e-6).alias("odds"), x["kind"].alias("kind"), x["start"].alias("start"), x["end"].alias("end")))
    none = way(F.lit(0.0), F.lit(0), F.lit(-1))

    def best(ways: Column) -> Column:
        return F.aggregate(ways, none, lambda a, b: F.when(b["total"] > a["total"], b).otherwise(a))

    def step(ways: Column, x: Column) -> tuple[Column, Column]:
        ended = best(F.filter(ways, lambda w: w["end"] <= x["start"]))
        mine = way(ended["total"] + x["odds"], x["end"], x["i"])
        now = F.concat(F.array(ended, mine), F.filter(ways, lambda w: w["end"] > x["start"]))
        return now, F.struct(x["i"].alias("i"), ended["at"].alias("before"), mine["total"].alias("total"), x["kind"].alias("kind"), x["start"].alias("start"), x["end"].alias("end"))

    out = F.struct(F.lit(0).alias("i"), F.lit(0).alias("before"), F.lit(0.0).alias("total"), F.lit("").alias("kind"), F.lit(0).alias("start"), F.lit(0).alias("end"))
    ways = _scan(numbered, F.array(none), out, step)
    last = F.aggregate(ways, F.struct(F.lit(0.0).alias("total"), F.lit(-1).alias("at")), lambda a, x: F.when(x["total"] > a["total"], F.struct(x["total"].alias("total"), x["i"].alias("at"))).otherwise(a))

    def follow(at: Column, x: Column) -> tuple[Column, Column]:
        here = x["i"] == at
        return F.when(here, x["before"]).otherwise(at), F.struct(here.alias("stays"), x["kind"].alias("kind"), x["start"].alias("start"), x["end"].alias("end"))

    mark = F.struct(F.lit(False).alias("stays"), F.lit("").alias("kind"), F.lit(0).alias("start"), F.lit(0).alias("end"))
    kept = F.filter(F.reverse(_scan(F.reverse(ways), last["at"], mark, follow)), lambda x: x["stays"])
    return F.transform(kept, lambda x: F.struct(x["kind"].alias("kind"), x["start"].alias("start"), x["end"].alias("end")))


def detected(docs: DataFrame, table_rows: list[tuple[str, str, int, bool]] | None = None) -> DataFrame:
    """doc_id, text, base, added (arrays of kind, start, end): one row a document."""
    model = _own_model(docs.sparkSession) if table_rows is None else trained(docs.sparkSession, table_rows)
    rows = with_candidates(with_base(docs))
    rows = rows.select("doc_id", "text", "base", F.concat(*(_selected(k, model[k]) for k in KINDS)).alias("chosen"))
    item = lambda x, odds, kind: F.struct(x["start"].alias("start"), x["end"].alias("end"), kind.alias("kind"), odds.alias("odds"))
    as_base = F.transform("base", lambda x: item(x, F.lit(None).cast("double"), F.lit(None).cast("string")))
    every = F.array_sort(F.concat(as_base, F.transform("chosen", lambda x: item(x, x["odds"], x["kind"]))))
    none = F.array().cast("array<struct<kind:string,start:int,end:int>>")
    # each step is a column of its own: an expression that is used twice would be computed twice
    rows = rows.withColumn("chosen", F.when(F.size("chosen") > 0, every))
    rows = rows.withColumn("chosen", F.when(F.col("chosen").isNotNull(), _free(F.col("chosen"))))
    return rows.select("doc_id", "text", "base", F.when(F.size("chosen") > 0, _heaviest(F.col("chosen"))).otherwise(none).alias("added"))


def _listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")


def _of(spans: Column | str, kind: str) -> Column:
    return F.filter(spans, lambda x: x["kind"] == kind)


#: Spans of a text up to which its pieces are cut from the text itself; beyond it they are cut from its characters, in linear time.
FEW = 64


def redacted(docs: DataFrame, table_rows: list[tuple[str, str, int, bool]] | None = None) -> DataFrame:
    """doc_id, text with every span replaced by its kind in brackets."""
    rows = detected(docs, table_rows).withColumn("all", F.array_sort(F.transform(F.concat("base", "added"), lambda x: F.struct(x["start"], x["end"], x["kind"]))))

    def step(at: Column, x: Column) -> tuple[Column, Column]:
        label = F.when(x["end"] > at, F.concat(F.lit("["), x["kind"], F.lit("]"))).otherwise("")
        return F.greatest(at, x["end"]), F.struct(at.alias("from"), F.greatest(x["start"] - at, F.lit(0)).alias("n"), label.alias("label"), F.greatest(at, x["end"]).alias("to"))

    out = F.struct(F.lit(0).alias("from"), F.lit(0).alias("n"), F.lit("").alias("label"), F.lit(0).alias("to"))
    rows = rows.withColumn("cuts", F.when(F.size("all") > 0, _scan(F.col("all"), F.lit(0), out, step)))
    last = F.element_at("cuts", -1)["to"]
    few = F.concat(F.array_join(F.transform("cuts", lambda c: F.concat(F.substring(F.col("text"), c["from"] + 1, c["n"]), c["label"])), ""), F.substring(F.col("text"), last + 1, F.length("text")))
    rows = rows.withColumn("chars", F.when(F.size("cuts") > FEW, F.split("text", "")))
    part = lambda at, n: F.array_join(F.slice("chars", at + 1, n), "")
    many = F.concat(F.array_join(F.transform("cuts", lambda c: F.concat(part(c["from"], c["n"]), c["label"])), ""), part(last, F.size("chars")))
    text = F.when(F.col("cuts").isNull(), F.col("text")).when(F.col("chars").isNull(), few).otherwise(many)
    return rows.select("doc_id", text.alias("text"))


def op5_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = detected(table(spark, sf_dir, "documents"))
    counts = [F.size(_of("base", k)).cast("long").alias(f"n_{k}") for k in KINDS]
    by_kind = [F.sort_array(_of(F.concat("base", "added"), k)) for k in KINDS]
    return found.select("doc_id", *counts, F.sha2(_listed(F.col("base")), 256).alias("base_sha256"), _listed(F.concat(*by_kind)).alias("spans"))
