"""Personal data by candidate gradient boosting, with DataFrame and SQL functions only.

Base spans are the matches of four strict patterns that pass their checks; they always count.
High-recall generators propose further spans (addresses written out, numbers in looser
formats), which may overlap.  Every candidate gets yes/no features of its format and of the
text around it.  Boosted trees of depth two are fitted on all candidates of the corpus, which
one aggregate folds into at most 2^features distinct feature rows.  A candidate counts as
personal data there by a weak label that doesn't ask whether it is a base span: a valid form
of its kind (parts, Luhn, length; a cue where the form leaves doubt) with clean edges.  Rows
weigh in the fit by the logarithm of their count, so that a rare form is learned as well.
Scores are calibrated on the proposals that overlap no base span, by the share of weak labels
as a function that rises with the score; one is added if its calibrated score reaches
``least``, the better of two overlapping ones first.

Positions come from the pieces between the matches of a pattern: the running sum of the
lengths of pieces and matches, taken in blocks, so that a text with very many matches costs
no more than in proportion.

Cases: null text is empty and has no spans; texts of any length are read whole; repeated rows
give a row each; equal spans of a kind count once; other columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KINDS = ("email", "ip", "card", "phone")
#: Base patterns.  Possessive runs and the look-behinds only spare vain starts within a run; the matches are those of the plain patterns.
BASE = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++(?:\.[0-9]++)(?:\.[0-9]++)(?:\.[0-9]++)",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: Generators of further candidates, by the kind they propose.
LOOSE = [
    ("email", r"[A-Za-z0-9._%+-]{1,64}+\x20?(?:@|\(at\)|\[at\])\x20?[A-Za-z0-9-]{1,63}+(?:\x20?(?:\.|\(dot\)|\[dot\])\x20?[A-Za-z0-9-]{1,63}+)++"),
    ("email", r"[A-Za-z0-9._%+-]{1,64}+\x20?(?:@|\(at\)|\[at\])\x20?[A-Za-z0-9-]{1,63}+(?:(?:\.|\x20\.\x20|\x20?(?:\(dot\)|\[dot\])\x20?)[A-Za-z0-9-]{1,63}+)++"),
    ("ip", r"(?<![0-9])[0-9]{1,3}+(?:\x20?(?:\.|\[\.\]|\(\.\))\x20?[0-9]{1,3}+){3}"),
    ("card", r"(?<![0-9])[0-9]{3,6}+(?:[\x20.-][0-9]{3,6}+){2,4}"),
    ("card", r"(?<![0-9])[0-9]{4}([\x20.-])(?:[0-9]{4}\1[0-9]{4}\1[0-9]{4}|[0-9]{6}\1[0-9]{5})(?![0-9])"),
    ("phone", r"(?:\+\x20?[0-9]{1,3}+[\x20.-]?)?\(?[0-9]{3}\)?[\x20.-]?[0-9]{3}[\x20.-][0-9]{4}(?![0-9])"),
]
#: Column that tells whether a text can match at all; spares most texts the patterns.
HINT = {"email": "__at", "ip": "__digit", "card": "__digit", "phone": "__digit"}
#: Words of the text around a span that speak of personal data.
CUES = r"(?i)(?:mail|contact|phone|call|tel|mobile|fax|card|visa|account|pay|host|address|server|login|ip)[a-z]*[\x20:=]*\z"
FEATURES = ("is_email", "is_ip", "is_card", "is_phone", "digits_8_15", "digits_16_19", "octets", "luhn", "plus", "spaced", "clean_left", "clean_right", "cue", "form")
#: Weak labels that hold everywhere, as rows (bits, candidates, personal) of the feature table: an address with
#: a part over 255, a card number of another length or with a wrong check digit, a telephone number of another
#: length, and anything that begins or ends within a word are no personal data.
_bit = {f: 1 << k for k, f in enumerate(FEATURES)}
_clean = _bit["clean_left"] | _bit["clean_right"]
#: The valid form with clean edges is, also where the corpus has none of a kind.
PRIOR = [
    *[(_bit["is_ip"] | _clean | x, 50, 0) for x in (0, _bit["spaced"], _bit["cue"], _bit["digits_8_15"])],
    *[(_bit["is_card"] | _clean | x, 50, 0) for x in (0, _bit["digits_8_15"], _bit["digits_16_19"], _bit["digits_8_15"] | _bit["luhn"], _bit["digits_16_19"] | _bit["spaced"], _bit["digits_8_15"] | _bit["luhn"] | _bit["spaced"])],
    *[(_bit["is_phone"] | _clean | x, 50, 0) for x in (0, _bit["plus"], _bit["spaced"], _bit["digits_16_19"])],
    *[(_bit[k] | _bit[side] | x, 50, 0) for k, x in (("is_email", 0), ("is_ip", _bit["octets"]), ("is_card", _bit["digits_16_19"] | _bit["luhn"]), ("is_phone", _bit["digits_8_15"])) for side in ("clean_left", "clean_right") for x in (x, x | _bit["form"])],
    *[(_bit[k] | _bit["form"] | _clean | x, 50, 50) for k, x in (("is_email", 0), ("is_email", _bit["spaced"]), ("is_ip", _bit["octets"]), ("is_ip", _bit["octets"] | _bit["spaced"]), ("is_card", _bit["digits_16_19"] | _bit["luhn"]), ("is_card", _bit["digits_8_15"] | _bit["luhn"]), ("is_phone", _bit["digits_8_15"]), ("is_phone", _bit["digits_8_15"] | _bit["spaced"]))],
]
BLOCK = 256
SPAN = "array<struct<kind:int,start:bigint,end:bigint,text:string,left:string,right:string>>"


def running(lens: str) -> str:
    """SQL: exclusive running sums of an array of bigint, plus the total at the end; blockwise."""
    n = f"CAST(ceil(size({lens}) / {BLOCK}.0) AS int)"
    blocks = f"transform(sequence(0, greatest({n} - 1, 0)), b -> slice({lens}, b * {BLOCK} + 1, {BLOCK}))"
    sums = f"transform({blocks}, x -> aggregate(x, 0L, (s, v) -> s + v))"
    base = f"aggregate({sums}, array(0L), (s, v) -> array_append(s, element_at(s, -1) + v))"
    return f"flatten(zip_with({blocks}, slice({base}, 1, greatest({n}, 1)), (x, o) -> slice(aggregate(x, array(o), (s, v) -> array_append(s, element_at(s, -1) + v)), 1, size(x))))"


def matches(df: DataFrame, pattern: str, hint: str, name: str, kind: int) -> DataFrame:
    """Adds column ``name``: all matches with positions in code points and the text beside them."""
    hit = F.col(hint)
    none = F.expr("CAST(array() AS array<string>)")
    p = F.lit(pattern)
    df = df.withColumn("__m", F.when(hit, F.regexp_extract_all("__text", p, F.lit(0))).otherwise(none))
    df = df.withColumn("__p", F.when(F.size("__m") > 0, F.split("__text", pattern, -1)).otherwise(none))
    df = df.withColumn("__l", F.expr("zip_with(__m, slice(__p, 1, size(__m)), (m, p) -> CAST(length(m) + length(p) AS bigint))"))
    df = df.withColumn("__o", F.when(F.size("__m") > 0, F.expr(running("__l"))).otherwise(F.expr("CAST(array() AS array<bigint>)")))
    span = f"""transform(__m, (m, i) -> named_struct('kind', {kind}, 'start', __o[i] + length(__p[i]), 'end', __o[i] + length(__p[i]) + length(m),
        'text', m, 'left', right(__p[i], 24), 'right', left(__p[i + 1], 8)))"""
    return df.withColumn(name, F.expr(f"CAST({span} AS {SPAN})")).drop("__m", "__p", "__l", "__o")


def digits(text: str) -> str:
    return f"regexp_replace({text}, '[^0-9]', '')"


def luhn(d: str) -> str:
    """SQL: whether a string of digits passes the Luhn check."""
    at = f"CAST(substring({d}, length({d}) - k, 1) AS int)"
    return f"aggregate(sequence(0, length({d}) - 1), 0, (s, k) -> s + IF(k % 2 = 0, {at}, 2 * {at} - IF({at} > 4, 9, 0))) % 10 = 0"


def octets(text: str) -> str:
    return f"size(split({text}, '[^0-9]+')) = 4 AND forall(split({text}, '[^0-9]+'), o -> length(ltrim('0', o)) <= 3 AND CAST(right(concat('000', ltrim('0', o)), 3) AS int) <= 255)"


#: SQL checks of the base matches; x is the span.
CHECK = {
    "email": "true",
    "ip": octets("x.text"),
    "card": f"length({digits('x.text')}) BETWEEN 16 AND 19 AND {luhn(digits('x.text'))}",
    "phone": f"length({digits('x.text')}) BETWEEN 8 AND 15",
}


def hinted(df: DataFrame) -> DataFrame:
    at = F.col("__text").contains("@") | F.col("__text").contains("(at)") | F.col("__text").contains("[at]")
    return df.withColumn("__at", at).withColumn("__digit", F.col("__text").rlike("[0-9]"))


def base_spans(df: DataFrame) -> DataFrame:
    """Column ``__base``: the checked spans, by kind as listed and then by start."""
    for k, kind in enumerate(KINDS):
        df = matches(df, BASE[kind], HINT[kind], f"__b{k}", k)
    return df.withColumn("__base", F.concat(*[F.expr(f"filter(__b{k}, x -> {CHECK[kind]})") for k, kind in enumerate(KINDS)])).drop(*[f"__b{k}" for k in range(len(KINDS))])


def proposals(df: DataFrame) -> DataFrame:
    """Column ``__loose``: the spans of the generators, once each."""
    for g, (kind, pattern) in enumerate(LOOSE):
        df = matches(df, pattern, HINT[kind], f"__g{g}", KINDS.index(kind))
    every = F.array_distinct(F.concat(*[F.col(f"__g{g}") for g in range(len(LOOSE))]))
    return df.withColumn("__loose", every).drop(*[f"__g{g}" for g in range(len(LOOSE))])


def form(x: str) -> str:
    """SQL: whether span x has a valid form of its kind; forms that leave doubt need a cue."""
    d, cue = digits(f"{x}.text"), f"{x}.left RLIKE '{CUES.replace(chr(92), chr(92) * 2)}'"
    at, dot = r"\\x20?(?:@|\\(at\\)|\\[at\\])\\x20?", r"(?:\\.|\\x20?(?:\\(dot\\)|\\[dot\\])\\x20?)"
    name, host = "^[A-Za-z0-9_%+][A-Za-z0-9._%+-]*", "[A-Za-z0-9-]+"
    apart = f"{x}.text RLIKE '{name}{at}{host}(?:{dot}{host})*{dot}[A-Za-z]{{2,24}}$'"
    blank = rf"{x}.text RLIKE '{name}{at}{host}(?:(?:{dot}|\\x20\\.\\x20){host})*(?:{dot}|\\x20\\.\\x20)[A-Za-z]{{2,24}}$'"
    usual = rf"{x}.text RLIKE '[.\\x20](?:com|org|net|edu|gov|info|biz)$'"
    alone = rf"NOT {x}.left RLIKE '[0-9][.-]\\z' AND NOT {x}.right RLIKE '^[.-][0-9]'"
    once = rf"NOT {x}.left RLIKE '(?:[02-9]|[0-9.-]1)[.-]\\z' AND NOT {x}.right RLIKE '^[.-][0-9]'"
    n = f"length({d})"
    return f"""CASE {x}.kind WHEN 0 THEN {apart} OR {blank} AND ({usual} OR {cue})
        WHEN 1 THEN {octets(f'{x}.text')} AND {alone} AND ({x}.text NOT LIKE '% %' OR {x}.text RLIKE '[\\\\[(]' OR {cue})
        WHEN 2 THEN {n} BETWEEN 13 AND 19 AND {luhn(d)} AND {alone} AND ({n} >= 15 OR {cue})
        ELSE {n} BETWEEN 10 AND 15 AND {once} AND ({x}.text RLIKE '[+().-]' OR {cue}) END"""


def weak_label(bits: str) -> str:
    """SQL: whether features ``bits`` are those of personal data: a valid form between clean edges."""
    every = _clean | _bit["form"]
    return f"IF(({bits} & {every}) = {every}, 1, 0)"


def feature_bits(x: str) -> str:
    """SQL: the features of span x as the bits of an int, in the order of FEATURES."""
    d = digits(f"{x}.text")
    tests = [
        *[f"{x}.kind = {k}" for k in range(4)],
        f"length({d}) BETWEEN 8 AND 15",
        f"length({d}) BETWEEN 16 AND 19",
        f"{x}.kind = 1 AND {octets(f'{x}.text')}",
        f"{x}.kind = 2 AND length({d}) BETWEEN 12 AND 19 AND {luhn(d)}",
        f"startswith({x}.text, '+')",
        rf"{x}.text RLIKE '[\\x20\\[(]'",
        rf"{x}.left RLIKE '(?:^|[^\\p{{L}}\\p{{N}}])\\z'",
        rf"{x}.right RLIKE '^(?:$|[^\\p{{L}}\\p{{N}}])'",
        f"{x}.left RLIKE '{CUES.replace(chr(92), chr(92) * 2)}'",
        form(x),
    ]
    return " + ".join(f"IF({t}, {1 << k}, 0)" for k, t in enumerate(tests))


def feature_table(spanned: DataFrame) -> list[tuple[int, int, int, int]]:
    """(feature bits, candidates, personal by weak label, proposals beside the base spans) over all candidates of the corpus; at most 2^features rows."""
    rows = spanned.select(F.expr(f"""concat(transform(__base, x -> named_struct('bits', {feature_bits('x')}, 'open', 0)),
        transform(filter(__loose, x -> NOT exists(__base, b -> b.start < x.end AND x.start < b.end)), x -> named_struct('bits', {feature_bits('x')}, 'open', 1)))""").alias("c"))
    # The outer form keeps the optimizer from inferring a filter, which would run the patterns twice.
    table = rows.select(F.explode_outer("c").alias("c")).filter("c is not null").groupBy("c.bits").agg(F.count("*").alias("n"), F.sum(F.expr(weak_label("c.bits"))).alias("y"), F.sum("c.open").alias("open"))
    return sorted(tuple(r) for r in table.collect())


def boost(table: list[tuple[int, ...]], rounds: int = 60, rate: float = 0.3, l2: float = 1.0) -> dict:
    """Depth-two trees by second-order gradient boosting of the logistic loss over the folded table, rows weighed by the logarithm of their count."""
    bits = [r[0] for r in table]
    n = [10 * (1 + math.log2(r[1])) for r in table]
    y = [w * r[2] / r[1] for w, r in zip(n, table)]
    total, pos = sum(n), sum(y)
    start = math.log((pos + 0.5) / (total - pos + 0.5)) if total else 0.0
    f, trees, m = [start] * len(bits), [], len(FEATURES)
    for _ in range(rounds if 0 < pos < total else 0):
        p = [1 / (1 + math.exp(-v)) for v in f]
        g = [a - b * q for a, b, q in zip(y, n, p)]
        h = [b * q * (1 - q) for b, q in zip(n, p)]

        def sums(rows):
            return sum(g[r] for r in rows), sum(h[r] for r in rows)

        def split(rows):
            best = (1e-9, None)
            a, b = sums(rows)
            for k in range(m):
                yes = [r for r in rows if bits[r] >> k & 1]
                c, d = sums(yes)
                gain = c * c / (d + l2) + (a - c) ** 2 / (b - d + l2) - a * a / (b + l2)
                best = max(best, (gain, k), key=lambda x: x[0])
            return best[1]

        def leaf(rows):
            a, b = sums(rows)
            return rate * a / (b + l2)

        def grow(rows, depth):
            k = split(rows) if depth and rows else None
            if k is None:
                return leaf(rows)
            return k, grow([r for r in rows if bits[r] >> k & 1], depth - 1), grow([r for r in rows if not bits[r] >> k & 1], depth - 1)

        tree = grow(range(len(bits)), 2)
        trees.append(tree)
        f = [v + value(tree, b) for v, b in zip(f, bits)]
    return {"start": start, "trees": trees, "cut": None, "table": [(v, r[3], r[3] * r[2] / r[1]) for v, r in zip(f, table) if len(r) > 3 and r[3]]}


def value(tree, bits: int) -> float:
    while isinstance(tree, tuple):
        tree = tree[1] if bits >> tree[0] & 1 else tree[2]
    return tree


def calibrated_cut(model: dict, least: float) -> float:
    """The least raw score whose calibrated value, the rising function of the score nearest to the weak labels of the proposals, is ``least`` at least."""
    blocks: list[list[float]] = []
    for f, n, y in sorted(model["table"], reverse=True):
        blocks.append([f, n, y])
        while len(blocks) > 1 and (blocks[-2][0] - f < 1e-9 or blocks[-2][2] * blocks[-1][1] < blocks[-1][2] * blocks[-2][1]):
            _, a, b = blocks.pop(-2)
            blocks[-1] = [f, blocks[-1][1] + a, blocks[-1][2] + b]
    return min((f for f, n, y in blocks if y >= least * n), default=math.inf)


def tree_sql(tree, bits: str) -> str:
    if not isinstance(tree, tuple):
        return f"{tree!r}D"
    return f"IF(({bits} & {1 << tree[0]}) <> 0, {tree_sql(tree[1], bits)}, {tree_sql(tree[2], bits)})"


def added_spans(df: DataFrame, model: dict, least: float) -> DataFrame:
    """Column ``__added``: proposed spans that reach the threshold and overlap no base span nor a better one."""
    cut = calibrated_cut(model, least)
    none = F.expr(f"CAST(array() AS {SPAN})")
    if cut == math.inf or not model["trees"]:
        return df.withColumn("__added", none)
    score = " + ".join([f"{model['start']!r}D", *[tree_sql(t, "c.bits") for t in model["trees"]]])
    open_ = "filter(__loose, x -> NOT exists(__base, b -> b.start < x.end AND x.start < b.end))"
    df = df.withColumn("__c", F.expr(f"transform({open_}, x -> named_struct('x', x, 'bits', {feature_bits('x')}))"))
    df = df.withColumn("__c", F.when(F.size("__c") > 0, F.expr(f"filter(transform(__c, c -> named_struct('score', {score}, 'x', c.x)), c -> c.score >= {cut - 1e-9!r}D)")))
    better = "(d.score > c.score OR d.score = c.score AND (d.x.start < c.x.start OR d.x.start = c.x.start AND (d.x.kind < c.x.kind OR d.x.kind = c.x.kind AND d.x.end > c.x.end)))"
    chosen = f"transform(filter(__c, c -> NOT exists(__c, d -> d.x.start < c.x.end AND c.x.start < d.x.end AND {better})), c -> c.x)"
    return df.withColumn("__added", F.when(F.size("__c") > 0, F.expr(chosen)).otherwise(none)).drop("__c")


def find(docs: DataFrame, *, text_col: str = "text", keep: tuple = (), least: float = 0.995, model: dict | None = None) -> DataFrame:
    """The columns in ``keep`` and __text, __base and __added of every document."""
    rows = docs.select(*[F.col(f"`{c}`") for c in keep], F.coalesce(F.col(f"`{text_col}`").cast("string"), F.lit("")).alias("__text"))
    rows = hinted(rows)
    spanned = proposals(base_spans(rows)).drop("__digit", "__at")
    model = model or boost(feature_table(spanned) + PRIOR)
    return added_spans(spanned, model, least).drop("__loose")


def digest(spans: str) -> str:
    name = "element_at(array('email', 'ip', 'card', 'phone'), x.kind + 1)"
    return f"array_join(transform(array_sort(transform({spans}, x -> named_struct('kind', x.kind, 'start', x.start, 'end', x.end))), x -> concat({name}, ':', x.start, ':', x.end)), ',')"


def report(found: DataFrame, id_col: str = "doc_id") -> DataFrame:
    every = "array_distinct(transform(concat(__base, __added), x -> named_struct('kind', x.kind, 'start', x.start, 'end', x.end)))"
    return found.select(
        F.col(id_col).cast("long").alias("doc_id"),
        *[F.expr(f"CAST(size(filter(__base, x -> x.kind = {k})) AS bigint)").alias(f"n_{kind}") for k, kind in enumerate(KINDS)],
        F.sha2(F.expr(digest("__base")).cast("binary"), 256).alias("base_sha256"),
        F.expr(digest(every)).alias("spans"),
    )


def redact(docs: DataFrame, *, text_col: str = "text", length_col: str | None = "n_chars", least: float = 0.995) -> DataFrame:
    """The documents with every found span replaced by its kind in brackets; other columns stay, the length column follows."""
    names = docs.columns
    found = find(docs, text_col=text_col, keep=tuple(names), least=least)
    found = found.withColumn("__s", F.expr("""array_sort(transform(concat(__base, __added), x -> named_struct('start', x.start, 'end', x.end, 'kind', x.kind)))"""))
    # Overlapping spans are one; its kind is that of the first.
    merged = """aggregate(__s, CAST(array() AS array<struct<start:bigint,end:bigint,kind:int>>), (a, x) ->
        IF(size(a) > 0 AND element_at(a, -1).end > x.start,
           array_append(slice(a, 1, size(a) - 1), named_struct('start', element_at(a, -1).start, 'end', greatest(element_at(a, -1).end, x.end), 'kind', element_at(a, -1).kind)),
           array_append(a, x)))"""
    found = found.withColumn("__s", F.when(F.size("__s") > 0, F.expr(merged)))
    label = "element_at(array('[EMAIL]', '[IP]', '[CARD]', '[PHONE]'), x.kind + 1)"
    text = f"""concat(array_join(transform(__s, (x, i) -> concat(substring(__text, CAST(IF(i = 0, 0, __s[i - 1].end) AS int) + 1, CAST(x.start - IF(i = 0, 0, __s[i - 1].end) AS int)), {label})), ''),
        substring(__text, CAST(element_at(__s, -1).end AS int) + 1))"""
    found = found.withColumn("__new", F.when(F.size("__s") > 0, F.expr(text)).otherwise(F.col(f"`{text_col}`")))

    def out(c: str) -> Column:
        if c == text_col:
            return F.col("__new").alias(c)
        if c == length_col:
            return F.when(F.size("__s") > 0, F.length("__new")).otherwise(F.col(f"`{c}`")).cast(docs.schema[c].dataType).alias(c)
        return F.col(f"`{c}`")

    return found.select(*[out(c) for c in names])
