"""Personal data and secrets by candidate gradient boosting, in DataFrame operations only.

Four fixed kinds (email, ip, card, phone) are found by pattern and check. Beside these, high-recall generators propose further
spans of eight kinds, some kinds by several generators, and spans of different generators may overlap. Boosted trees, one model
for each kind, score a candidate from its format and from the text on both sides; a candidate whose score passes its kind's
calibrated threshold, and that overlaps no fixed span, is added; of added ones that overlap, the higher score stays. No table
labels personal data, so trees and thresholds are fitted on the driver to a fixed number of generated examples, whose features
come from the same expressions, and the trees are scored as one SQL expression. Positions count code points.

Null texts count as empty. A text is worked on whole, its matches in runs of a fixed length, so that very many matches cost no
more than their number; two private-use signs that mark matches count as "?" where a text holds them. Repeated rows give
repeated rows, equal scores keep the span that comes first; empty tables give empty results. Other columns pass through, but
those named like a result (n_email, n_ip, n_card, n_phone, base, spans) are replaced.
"""

from __future__ import annotations

import random

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .boosting import Boosted, Isotonic

#: The kinds and their patterns, with possessive repeats (same matches, no deep recursion).
KINDS = ["email", "ip", "card", "phone"]
PATTERNS = {
    "email": r"[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
TRIGGERS = {"email": r"[A-Za-z0-9._%+-]@[A-Za-z0-9-]", "ip": r"[0-9]\.[0-9]+\.[0-9]", "card": r"[0-9](?:[\x20-]?[0-9]){11}", "phone": r"\+[0-9]"}
HEX, CAPITAL, SMALL = "[0-9A-Fa-f]", "[A-ZÀ-ÖØ-Þ]", "[a-zß-öø-ÿ]"
STREET = "Street|St|Avenue|Ave|Road|Rd|Lane|Ln|Drive|Dr|Boulevard|Blvd"
TITLE = "Mr|Mrs|Ms|Dr|Herr|Frau|Mme|Monsieur|Madame|Señor|Señora"
_USER, _HOST, _TLD = "[A-Za-z0-9._%+-]{2,64}", "[A-Za-z0-9-]{2,64}", "[A-Za-z]{2,24}"
_AT, _DOT = r"[(\[{]\x20?at\x20?[)\]}]", r"[(\[{]\x20?dot\x20?[)\]}]|\sdot\s"
#: (kind, pattern, trigger): a text without the trigger has no match of the pattern.
GENERATORS = [
    ("handle", rf"(?i:{_USER}(?:\s?(?:{_AT})\s?|\s@\s?|@\s){_HOST}(?:\s?(?:{_DOT})\s?|\.){_TLD})", rf"(?i:{_AT})|\s@|@\s"),
    ("handle", rf"(?i:{_USER}\s?(?:{_AT}|@|\sat\s)\s?{_HOST}\s?(?:{_DOT})\s?{_TLD})", rf"(?i:{_DOT})"),
    ("number", r"[0-9(][0-9().\x20/-]{5,28}[0-9]", r"[0-9][0-9().\x20/-]{5}"),
    ("number", r"(?:\([0-9]{2,5}\)\x20?)?[0-9]{2,5}(?:[./-][0-9]{2,7}){1,5}", r"[0-9]{2}[./-][0-9]{2}"),
    ("secret", r"\b(?=[A-Za-z+/_=-]{0,40}[0-9])[A-Za-z0-9+/_=-]{20,200}", r"\b(?=[A-Za-z+/_=-]{0,40}[0-9])[A-Za-z0-9+/_=-]{20}"),
    ("secret", r"(?i:\b(?:password|passwd|pwd|secret|token|api[_-]?key)[\x22']?\s{0,3}[:=]\s{0,3}[\x22']?[^\s\x22']{6,200})", r"(?i:(?:password|passwd|pwd|secret|token|key)[\x22']?\s{0,3}[:=])"),
    ("iban", r"\b[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]{4}){2,7}(?:\x20?[A-Z0-9]{1,3})?\b", r"[A-Z]{2}[0-9]{2}\x20?[A-Z0-9]{4}"),
    ("ipv6", rf"(?:{HEX}{{1,4}}:){{7}}{HEX}{{1,4}}|(?:{HEX}{{1,4}}:){{1,6}}(?::{HEX}{{1,4}}){{1,6}}", rf"{HEX}:(?::|{HEX}{{1,4}}:)"),
    ("mac", rf"(?:{HEX}{{2}}[:-]){{5}}{HEX}{{2}}", rf"(?:{HEX}{{2}}[:-]){{5}}"),
    ("address", rf"[0-9]{{1,5}}\x20(?:{CAPITAL}{SMALL}{{1,20}}\x20){{1,3}}(?:{STREET})\b", rf"\x20(?:{STREET})\b"),
    ("address", rf"{CAPITAL}{SMALL}{{2,20}}(?:straße|strasse|weg|platz|allee)\x20[0-9]{{1,4}}[a-z]?\b", r"(?:straße|strasse|weg|platz|allee)\x20[0-9]"),
    ("name", rf"\b(?:{TITLE})\.?\x20{CAPITAL}{SMALL}{{1,20}}(?:\x20{CAPITAL}{SMALL}{{1,20}}){{0,2}}", rf"\b(?:{TITLE})\.?\x20{CAPITAL}"),
    ("name", rf"(?i:\b(?:name|nom|nombre)):\x20{CAPITAL}{SMALL}{{1,20}}(?:\x20{CAPITAL}{SMALL}{{1,20}}){{1,2}}", r"(?i:name|nom|nombre):\x20"),
]
ADDED = list(dict.fromkeys(kind for kind, *_ in GENERATORS))
FEATURES = ["chars", "digits", "groups", "first", "last", "dashes", "dots", "spaces", "slashes", "parens", "letters", "capitals", "variety", "colons", "hidden_at", "hidden_dot", "assigned", "hex", "checked", "words", "cue", "counter", "secret_cue", "glued", "quoted", "glued_right", "unit_right"]
CUE = r"(?i)\b(?:tel|phone|call|mobile|cell|fax|whatsapp|contact|ssn|social security|passport|iban|account|card|visa|mail|e-mail|write|reach|telefon|handy|téléphone|teléfono|móvil|address|live at|lives at|ship to|dear|signed|patient|contact)\b[^\n]{0,16}$"
COUNTER = r"(?i)\b(?:isbn|version|v|order|invoice|page|pages|date|id|no|ticket|build|pi|year|section|art|score|published|copyright|commit|sha|sha1|md5|checksum|hash|revision|digest|etag)\b[^\n]{0,8}$|[$€£%#][\x20]?$"
SECRET_CUE = r"(?i)(?:token|secret|password|passwd|pwd|api[_-]?key|access[_-]?key|private[_-]?key|credential|bearer|authorization)[\x22']?\s{0,3}[:=]?\s{0,3}[\x22']?$"
OPEN, SHUT = "\ue000", "\ue001"  # marks round a match; texts that hold them get "?" there
RUN = 256  # parts of a text that are folded together
SPAN = "struct<start:int,end:int,span:string,left:string,right:string>"
NO_SPANS = f"array<{SPAN}>"


def _parts(text: Column, pattern: str, trigger: str) -> Column:
    """text, match, text, ..., text for leftmost non-overlapping matches; null without the trigger."""
    return F.when(text.rlike(trigger), F.split(F.regexp_replace(text, f"({pattern})", f"{OPEN}$1{SHUT}"), f"[{OPEN}{SHUT}]", -1))


def _marked(parts: Column) -> Column:
    """array<struct(start, end, span, left, right)> of the matches in parts; left and right: 32 signs beside them."""

    def fold(parts: Column, at: Column, left: Column) -> Column:
        """A run of parts, of which the last is also the first of the next run."""
        start = F.struct(at.alias("at"), F.lit(0).alias("k"), F.array().cast(NO_SPANS).alias("found"), left.alias("left"), F.lit(None).cast(SPAN).alias("open"))

        def step(s: Column, x: Column) -> Column:
            end, odd, open_ = s["at"] + F.length(x), s["k"] % 2 == 1, s["open"]
            one = F.struct(s["at"].alias("start"), end.alias("end"), x.alias("span"), s["left"].alias("left"), F.lit("").alias("right"))
            shut = F.struct(open_["start"].alias("start"), open_["end"].alias("end"), open_["span"].alias("span"), open_["left"].alias("left"), F.left(x, F.lit(32)).alias("right"))
            return F.struct(end.alias("at"), (s["k"] + 1).alias("k"), F.when(odd | open_.isNull(), s["found"]).otherwise(F.concat(s["found"], F.array(shut))).alias("found"), F.right(x, F.lit(32)).alias("left"), F.when(odd, one.cast(SPAN)).alias("open"))

        return F.aggregate(parts, start, step, lambda s: s["found"])

    def runs(parts: Column) -> Column:
        which = F.sequence(F.lit(0), F.floor((F.size(parts) - 1) / RUN).cast("int"))
        cut = F.transform(which, lambda i: F.slice(parts, i * RUN + 1, F.lit(RUN + 1)))
        # Where each run begins: the lengths of all runs before, each without the part it shares with the next.
        size = lambda run: F.aggregate(F.slice(run, F.lit(1), F.lit(RUN)), F.lit(0), lambda a, x: a + F.length(x))
        begin = F.aggregate(cut, F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("all")), lambda s, run: F.struct((s["at"] + size(run)).alias("at"), F.concat(s["all"], F.array(s["at"])).alias("all")), lambda s: s["all"])
        return F.flatten(F.zip_with(cut, begin, lambda run, at: fold(run, at, F.lit(""))))

    none = parts.isNull() | (F.size(parts) < 2)
    return F.when(none, F.array().cast(NO_SPANS)).when(F.size(parts) <= RUN, fold(parts, F.lit(0), F.lit(""))).otherwise(runs(parts))


def _digits(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    n = F.length(digits)

    def part(i: Column) -> Column:
        d = F.substring(digits, n - i, F.lit(1)).cast("int") * (i % 2 + 1)
        return F.when(d > 9, d - 9).otherwise(d)

    return F.aggregate(F.sequence(F.lit(0), n - 1), F.lit(0), lambda a, i: a + part(i)) % 10 == 0


def _holds(kind: str, x: Column) -> Column:
    if kind == "email":
        return F.lit(True)
    if kind == "ip":
        parts = F.split(x, r"\.")
        return F.forall(parts, lambda p: (F.length(F.regexp_replace(p, "^0+", "")) <= 3) & (F.right(p, F.lit(3)).cast("int") <= 255))
    n = F.length(_digits(x))
    return F.when(n.between(12, 19), _luhn(_digits(x))).otherwise(False) if kind == "card" else n.between(9, 15)


def base_spans(parts: dict[str, str]) -> dict[str, Column]:
    """For each fixed kind its spans; parts: the column of each kind's ``_parts``."""

    def valid(kind: str) -> Column:
        return F.filter(_marked(F.col(parts[kind])), lambda m: _holds(kind, m["span"]))

    return {k: valid(k) for k in parts}


def _features(m: Column) -> Column:
    """struct of FEATURES (double) of one candidate."""
    span, groups = m["span"], F.split(F.regexp_replace(m["span"], "^[^0-9]+|[^0-9]+$", ""), "[^0-9]+")

    def count(pattern: str) -> Column:
        return F.regexp_count(span, F.lit(pattern)).cast("double")

    def flag(c: Column) -> Column:
        return c.cast("double")

    # ISO 13616: the first four signs go last, letters count from 10, and the number is 1 modulo 97.
    plain = F.regexp_replace(span, r"\x20", "")
    turned = F.concat(F.substring(plain, 5, 64), F.left(plain, F.lit(4)))
    value = lambda c: F.when(c.between("0", "9"), F.ascii(c) - 48).otherwise(F.ascii(c) - 55)
    mod97 = F.aggregate(F.split(turned, ""), F.lit(0), lambda a, c: F.when(c == "", a).otherwise((a * F.when(c.between("0", "9"), 10).otherwise(100) + value(c)) % 97))
    values = [
        *(c.cast("double") for c in (F.length(span), F.length(_digits(span)), F.size(groups), F.length(F.element_at(groups, 1)), F.length(F.element_at(groups, -1)))),
        count("-"), count(r"\."), count(r"\x20"), count("/"), count(r"\("), count(r"\p{L}"), count(r"\p{Lu}"),
        F.size(F.array_distinct(F.split(span, ""))).cast("double"), count(":"),
        flag(span.rlike(r"(?i)[(\[{]\x20?at\x20?[)\]}]|\sat\s|\s@|@\s")), flag(span.rlike(r"(?i)[(\[{]\x20?dot\x20?[)\]}]|\sdot\s")), flag(span.rlike(r"(?i)^(?:password|passwd|pwd|secret|token|api[_-]?key)[\x22']?\s{0,3}[:=]")),
        flag(span.rlike(f"^{HEX}+$")), flag(F.coalesce((mod97 == 1) & plain.rlike("^[A-Z]{2}[0-9]{2}[A-Z0-9]{8,30}$"), F.lit(False))), count(r"\p{L}{2,}"),
        flag(m["left"].rlike(CUE)), flag(m["left"].rlike(COUNTER)), flag(m["left"].rlike(SECRET_CUE)), flag(m["left"].rlike(r"[\p{L}\p{N}_.+-]$")), flag(m["left"].rlike(r"[\x22'=:]\x20?$") & m["right"].rlike(r"^[\x22']")),
        flag(m["right"].rlike(r"^(?:[\p{L}\p{N}_+@-]|\.[\p{L}\p{N}])")), flag(m["right"].rlike(r"(?i)^\x20?(?:%|€|\$|£|kg|km|cm|mm|ms|mb|gb|usd|eur|pages?|items?|years?|points?)\b")),
    ]
    return F.struct(*[v.alias(n) for n, v in zip(FEATURES, values, strict=True)])


def _examples(n: int, seed: int = 11) -> list[tuple[str, str, str, str, int]]:
    """(kind, left, span, right, personal) of n generated candidates."""
    g = random.Random(seed)
    pick = lambda signs, k: "".join(g.choice(signs) for _ in range(k))
    d = lambda k: pick("0123456789", k)
    w = lambda: pick("abcdefghilmnoprstuv", g.randint(2, 9))
    named = lambda: w().capitalize()
    hexes, mixed = "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"

    def iban(valid: bool) -> str:
        body, country = d(g.choice([12, 14, 16, 18])), pick("ABCDEFGHIKLNPST", 2)
        number = int(body + "".join(str(ord(c) - 55) for c in country) + "00")
        s = f"{country}{(98 - number % 97 + (0 if valid else g.randint(1, 95))) % 97:02d}{body}"
        return " ".join(s[k : k + 4] for k in range(0, len(s), 4)) if g.random() < 0.5 else s

    def one() -> tuple[str, str, str, str, int]:
        cue = g.choice(["tel: ", "Phone ", "call me at ", "mobile: ", "contact ", "fax ", "Telefon: ", "teléfono "])
        other = g.choice(["isbn ", "version ", "order ", "page ", "invoice no ", "id ", "$", "built ", w() + " ", w() + " ", w() + ", "])
        plain, after = w() + " ", g.choice([" " + w(), ". " + named(), ", " + w(), "\n", ""])
        match g.randrange(22):
            case 0 | 1 | 2:
                at, dot = g.choice(["(at)", " (at) ", "[at]", " at ", "{at}", " @ ", "@ "]), g.choice(["(dot)", " [dot] ", " dot ", "[dot]", "."])
                return "handle", g.choice(["mail ", plain, "write to "]), f"{w()}{at}{w()}{dot}{g.choice(['com', 'org', 'net', 'de', 'fr'])}", after, int(at != " at " or dot != ".")
            case 3:
                return "handle", plain, f"{w()} @ {w()}. {w()}" if g.random() < 0.5 else f"{w()} at {w()} dot {w()}", after, 0
            case 4 | 5:
                return "number", cue, g.choice([f"({d(3)}) {d(3)}-{d(4)}", f"{d(3)}-{d(3)}-{d(4)}", f"0{d(3)} {d(7)}", f"0{d(2)}/{d(7)}", f"{d(3)}.{d(3)}.{d(4)}", f"0{d(1)} {d(2)} {d(2)} {d(2)} {d(2)}"]), after, 1
            case 6:
                return "number", g.choice(["ssn ", "SSN: ", "social security ", plain, "passport "]), f"{d(3)}-{d(2)}-{d(4)}", after, 1
            case 7:
                return "number", g.choice([plain, "at "]), f"({d(3)}) {d(3)}-{d(4)}", after, 1
            case 8 | 9 | 10 | 11:
                span = g.choice([d(8), d(g.randint(9, 20)), d(16), d(16), f"{g.randint(1900, 2030)}-{g.randint(10, 12)}-{g.randint(10, 28)}", f"{g.randint(10, 28)}.{g.randint(10, 12)}.{g.randint(1900, 2030)}", f"{d(1)}.{d(2)}.{d(2)}.{d(3)}", f"978-{d(1)}-{d(4)}-{d(4)}-{d(1)}", f"{d(3)} {d(3)} {d(3)}", f"{d(4)} {d(4)}", f"{d(6)}.{d(2)}", f"{d(5)} {d(3)} {d(2)}", f"{d(2)}/{d(2)}/{d(4)}", f"{d(3)}.{d(3)}.{d(2)}.{d(3)}", f"{d(2)}-{d(2)}", f"{d(3)}-{d(4)}", f"{d(4)}-{d(4)}", f"{d(2)}.{d(3)}"])
                return "number", other, span, g.choice([after, " kg", " pages", "%"]), 0
            case 12 | 13:
                quote = g.choice(['"', "'", ""])
                key = g.choice(["token", "api_key", "secret", "access_key", "TOKEN", "Authorization: Bearer", "private_key", "password"])
                value = g.choice([pick(hexes, g.choice([32, 40, 64])), pick(hexes, 40).upper(), pick(mixed, g.randint(20, 48)) + d(1), "sk-" + pick(mixed, 32) + d(2), "ghp_" + pick(mixed, 34) + d(2), "AKIA" + pick("ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", 16)])
                return "secret", f"{w()} {key}{g.choice([' = ', '=', ': '])}{quote}"[-32:], value, quote + after, 1
            case 14:
                return "secret", plain, f"{g.choice(['password', 'pwd', 'token', 'secret', 'api_key'])}{g.choice([' = ', '=', ': '])}{g.choice(['', chr(34)])}{pick(mixed, g.randint(8, 40))}{d(2)}", after, 1
            case 15 | 16:
                span = g.choice([pick(hexes, 40), pick(hexes, 32), pick(hexes, 64), d(20), "-".join(w() for _ in range(5)) + d(2), "/".join(w() for _ in range(5)) + "/" + d(4), pick(hexes, 8) + "-" + "-".join(pick(hexes, 4) for _ in range(3)) + "-" + pick(hexes, 12), w() * 4 + d(1), "=" * 20 + d(1), f"token: {w()}", f"secret = {w()}", "key: " + w()])
                left = g.choice(["commit ", "sha1 ", "checksum ", "md5: ", "revision ", plain, plain, "img/", "see "]) if not span.startswith(("token", "secret", "key")) else plain
                return "secret", left, span, after, 0
            case 17:
                valid = g.random() < 0.6
                return "iban", g.choice(["IBAN ", "iban: ", "account ", plain]), iban(valid), after, int(valid)
            case 18:
                good = g.random() < 0.6
                return "ipv6", g.choice(["host ", "from ", plain]), ":".join(pick(hexes, 4) for _ in range(8)) if good and g.random() < 0.5 else f"{pick(hexes, 4)}:{pick(hexes, 4)}::{pick(hexes, 4)}:{d(1)}" if good else g.choice([f"{d(1)}:{d(2)}::{d(1)}", f"{w()[0]}::{d(1)}", f"add::{d(1)}", f"{d(2)}:{d(2)}::{d(2)}"]), after, int(good)
            case 19:
                good = g.random() < 0.7
                sign = g.choice(":-")
                return "mac", g.choice(["mac ", "device ", plain]), sign.join(pick(hexes, 2) for _ in range(6)) if good else "-".join(d(2) for _ in range(6)), after if good else g.choice(["-" + d(2), ":" + d(2), after]), int(good)
            case 20:
                good = g.random() < 0.7
                return "address", g.choice(["lives at ", "ship to ", "address: ", plain]) if good else other, f"{d(g.randint(1, 4))} {named()} {g.choice(['Street', 'Avenue', 'Road', 'Lane', 'St'])}" if g.random() < 0.6 else f"{named()}{g.choice(['straße', 'weg', 'platz'])} {d(2)}", after, int(good)
            case _:
                good = g.random() < 0.7
                return "name", g.choice([plain, "dear ", "signed ", "patient "]), f"{g.choice(['Mr', 'Mrs', 'Dr.', 'Herr', 'Frau', 'Señor'])} {named()} {named()}" if good else f"{g.choice(['Dr', 'St', 'Ms'])} {named()}", after if good else g.choice([" Street", " Road", "@" + w(), "-" + w()]), int(good)

    return [one() for _ in range(n)]


def fit(spark: SparkSession, examples: int = 6000, precision: float = 0.95) -> dict[str, tuple[Boosted, float]]:
    """kind -> (trees, least log odds). A third of the generated examples calibrates the threshold."""
    rows = _examples(examples)
    df = spark.createDataFrame([(k, *r) for k, r in enumerate(rows)], "k int, kind string, left string, span string, right string, y int")
    got = df.select("k", "kind", "y", _features(F.struct("span", "left", "right")).alias("f")).collect()  # as many as examples
    got.sort(key=lambda r: r.k)
    out = {}
    for kind in ADDED:
        own = [r for r in got if r.kind == kind]
        x, y = np.array([list(r.f) for r in own]), np.array([r.y for r in own], float)
        apart = np.arange(len(y)) % 3 == 0
        trees = Boosted(rounds=16, depth=3, rate=0.4).fit(x[~apart], y[~apart])
        score = trees.score(x[apart])
        sure = Isotonic().fit(score, y[apart])
        passing = score[sure(score) >= precision]
        out[kind] = (trees, float(passing.min()) if len(passing) else float("inf"))
    return out


def _chosen(spans: str) -> Column:
    """Of spans (start, rank, end, kind, score; score null: fixed) in order all fixed ones, and the best of the added ones that
    overlap each other and no fixed one. One sweep: ``held`` is the last added span that nothing has yet beaten."""
    kind = "struct<start:int,rank:int,end:int,kind:string,score:double>"
    start = F.struct(F.array().cast(f"array<{kind}>").alias("kept"), F.lit(None).cast(kind).alias("held"), F.lit(0).alias("fixed"))

    def step(s: Column, m: Column) -> Column:
        held, fixed = s["held"], m["score"].isNull()
        apart = held.isNotNull() & (held["end"] <= m["start"])
        lost = ~fixed & ((m["start"] < s["fixed"]) | F.coalesce((held["end"] > m["start"]) & (held["score"] >= m["score"]), F.lit(False)))
        kept = F.concat(s["kept"], F.when(apart, F.array(held)).otherwise(F.array().cast(f"array<{kind}>")), F.when(fixed, F.array(m)).otherwise(F.array().cast(f"array<{kind}>")))
        after = F.when(fixed, F.lit(None).cast(kind)).when(lost, F.when(apart, F.lit(None).cast(kind)).otherwise(held)).otherwise(m)
        return F.struct(kept.cast(f"array<{kind}>").alias("kept"), after.cast(kind).alias("held"), F.when(fixed, F.greatest(s["fixed"], m["end"])).otherwise(s["fixed"]).alias("fixed"))

    return F.aggregate(spans, start, step, lambda s: F.when(s["held"].isNull(), s["kept"]).otherwise(F.concat(s["kept"], F.array(s["held"]))))


def redactions(docs: DataFrame) -> DataFrame:
    """docs with n_email, n_ip, n_card, n_phone, base (fixed spans) and spans (all), both array<struct(start, rank, end, kind)> in order."""
    models = fit(docs.sparkSession)
    names = [f"c{k}" for k in range(len(docs.columns))]
    text = F.translate(F.coalesce(F.col(names[docs.columns.index("text")]), F.lit("")), OPEN + SHUT, "??")
    out = docs.toDF(*names).withColumn("text", text)
    # Parts are columns of their own, so that a text is searched once for each pattern.
    parts = {f"p_{k}": _parts(F.col("text"), PATTERNS[k], TRIGGERS[k]) for k in KINDS} | {f"q{k}": _parts(F.col("text"), pattern, trigger) for k, (_, pattern, trigger) in enumerate(GENERATORS)}
    out = out.select(*names, *[v.alias(n) for n, v in parts.items()])
    found = base_spans({k: f"p_{k}" for k in KINDS}) | {f"m{k}": F.transform(_marked(F.col(f"q{k}")), lambda m: F.struct(m["start"].alias("start"), m["end"].alias("end"), _features(m).alias("f"))) for k in range(len(GENERATORS))}
    out = out.select(*names, *[v.alias(n) for n, v in found.items()])
    kinds = [*KINDS, *ADDED]
    def listed(column: str, kind: str, score) -> Column:
        return F.transform(column, lambda m: F.struct(m["start"].alias("start"), F.lit(kinds.index(kind)).alias("rank"), m["end"].alias("end"), F.lit(kind).alias("kind"), score(m).cast("double").alias("score")))

    out = out.withColumn("all", F.concat(*[listed(k, k, lambda m: F.lit(None)) for k in KINDS]))
    scored = {}
    for k, (kind, *_) in enumerate(GENERATORS):
        trees, least = models[kind]
        score = trees.sql_text([f"m.f.{n}" for n in FEATURES])
        passing = f"m.score >= {least!r}D" if np.isfinite(least) else "false"
        scored[f"g{k}"] = F.expr(f"filter(transform(m{k}, m -> struct(m.start as start, m.end as end, ({score}) as score)), m -> {passing})")
    out = out.select(*names, *KINDS, "all", *[v.alias(n) for n, v in scored.items()])
    added = [listed(f"g{k}", kind, lambda m: m["score"]) for k, (kind, *_) in enumerate(GENERATORS)]
    out = out.withColumn("spans", F.when(F.greatest(*[F.size(f"g{k}") for k in range(len(GENERATORS))]) == 0, F.array_sort("all")).otherwise(_chosen_sorted("all", added)))
    bare = lambda c: F.array_sort(F.transform(c, lambda m: F.struct(m["start"].alias("start"), m["rank"].alias("rank"), m["end"].alias("end"), m["kind"].alias("kind"))))
    result = {f"n_{k}": F.size(k).cast("long") for k in KINDS} | {"base": bare("all"), "spans": bare("spans")}
    kept = [F.col(n).alias(c) for n, c in zip(names, docs.columns, strict=True) if c not in result]
    return out.select(*kept, *[v.alias(n) for n, v in result.items()])


def _chosen_sorted(fixed: str, added: list[Column]) -> Column:
    return _chosen(F.array_sort(F.concat(F.col(fixed), *added)))


def joined(spans: str) -> Column:
    """kind:start:end, comma-joined."""
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat(s["kind"], F.lit(":"), s["start"].cast("string"), F.lit(":"), s["end"].cast("string"))))


def redact(docs: DataFrame, mark: str = "█") -> DataFrame:
    """docs with the characters of all spans replaced by mark, one for one."""
    r = redactions(docs)
    piece = F.aggregate(
        "spans",
        F.struct(F.lit(0).alias("at"), F.lit("").alias("s")),
        lambda a, m: F.struct(F.greatest(a["at"], m["end"]).alias("at"), F.concat(a["s"], F.substring(F.col("text"), a["at"] + 1, F.greatest(m["start"] - a["at"], F.lit(0))), F.repeat(F.lit(mark), F.greatest(m["end"] - F.greatest(m["start"], a["at"]), F.lit(0)))).alias("s")),
        lambda a: F.concat(a["s"], F.substring(F.col("text"), a["at"] + 1, F.length("text"))),
    )
    return r.withColumn("text", F.when(F.size("spans") > 0, piece).otherwise(F.col("text"))).select(*docs.columns)
