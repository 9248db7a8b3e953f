"""Secret scan in DataFrame functions only: fixed patterns, and sliding-window entropy of candidate strings.

Positions come from splitting a text at a pattern's matches and adding up lengths, so a scan never
leaves the JVM and nothing is shuffled. Only texts that a cheap test finds to hold a match take the
longer way. Entropy of a class of characters is measured in every window of fixed width over a
candidate; a step takes one character in and one out and corrects the sum of c*log2(c) by the two
counts that change. Candidates on the allow list (UUIDs, repeated or running characters, examples) give
no span; the fixed patterns' spans stay in any case. Candidates are runs of 20 characters or more, without
or with digits, of hex, base64 (with its closing '='), URL-safe base64, or letters and digits; where a
digit does not set them apart from words, identifiers and paths, unusual neighbours of letters do. Shorter
strings, strings cut by other characters and windows under a class's threshold are not found.

Defined cases: null text counts as empty and has no spans; spans of different kinds may overlap;
candidates may be of any length; an empty table gives no rows; other columns are ignored or, in
redact(), kept as they are. Positions are code points, ends exclusive.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Patterns of the base kinds. Quantifiers with a least count find the same maximal runs as plain ones with a check of the length after them.
ASSIGN = r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"[0-9a-f]{24,}"
ASSIGN_LEAST = 6

KINDS = ("assign", "access", "hex")


LETTERS = "abcdefghijklmnopqrstuvwxyz"
#: After each letter those that words of the usual Latin-script languages hardly put there (under 2 in 10,000 pairs of letters); half of all pairs.
UNUSUAL = {
    "a": "jqz", "b": "bdfghkmnpqtvwxz", "c": "bdfgjmnpqsvwxyz", "d": "cfgjkmpqvxz", "e": "j", "f": "bcdghjkmnpqsvwxyz", "g": "cdfjkmpqvwxyz", "h": "dfjmqxy", "i": "juy",
    "j": "bcdfghijklmnopqrstuvwxyz", "k": "abcdfghjklmnopqrtuvwxyz", "l": "bcghjkmnpqrvwxz", "m": "cdfghjklnqrvwxyz", "n": "jx", "o": "hjqxyz", "p": "bcghjkmnqvwxz", "q": "abcdefghijklmnopqrstvwxyz", "r": "fjqx",
    "s": "fkvxz", "t": "dfgjkqx", "u": "jkuwyz", "v": "bcdfghjklmnpqrstuvwxyz", "w": "bcdfgjklmpqtuvwxyz", "x": "bdfghjklmnqrsuvwxyz", "y": "bcdfgjkmqruvxyz", "z": "bcdfghijklmnopqrstvwxyz",
}


def _mixed() -> str:
    """Four unusual places, each at most six characters after the one before; a place is an unusual pair of letters (not where a capital starts a word), a change between letter and digit, or a capital that starts no word of three letters or more."""
    pairs = [f"[{a}{a.upper()}](?=[{rest}])|{a.upper()}(?=[{rest.upper()}])" for a, rest in UNUSUAL.items()]
    place = "(?:" + "|".join([*pairs, "[A-Za-z](?=[0-9])", "[0-9](?=[A-Za-z])", "[a-z](?=[A-Z](?![a-z]))", "[A-Z](?=[a-z][A-Z])"]) + ")"
    return f"{place}(?:.{{0,5}}{place}){{3}}"


MIXED = _mixed()


@dataclass(frozen=True)
class CharClass:
    """Characters that count, the pattern of candidates, width of the window, entropy (bits) from which a window is hot, and what a candidate must hold, if anything, not to be words or a path."""

    name: str
    alphabet: str
    pattern: str
    width: int
    bits: float
    needs: str | None = None


#: No class asks for a digit. A base64 candidate without one, any of the URL-safe alphabet and any of letters and digits alone must be MIXED; the last have a lower threshold, as 26 letters give less entropy.
CLASSES = (
    CharClass("entropy_hex", "0123456789" + LETTERS[:6] + LETTERS[:6].upper(), r"(?<![0-9A-Za-z])[0-9A-Fa-f]{20,}(?![0-9A-Za-z])", 20, 3.0),
    CharClass("entropy_base64", LETTERS + LETTERS.upper() + "0123456789+/=", r"(?<![0-9A-Za-z+/])(?=[A-Za-z]*+[0-9+/])[0-9A-Za-z+/]{20,}+={0,2}", 20, 3.7, "[0-9]|" + MIXED),
    CharClass("entropy_base64url", LETTERS + LETTERS.upper() + "0123456789-_=", r"(?<![0-9A-Za-z_-])(?=[0-9A-Za-z]*+[_-])[0-9A-Za-z_-]{20,}+={0,2}", 20, 3.7, MIXED),
    CharClass("entropy_alnum", LETTERS + LETTERS.upper() + "0123456789=", r"(?<![0-9A-Za-z])[0-9A-Za-z]{20,}+={0,2}", 20, 3.0, MIXED),
)
#: A candidate that one of these finds is suppressed.
ALLOW = (r"^(.)\1+$", r"(?i)example|0123456789|abcdefghij", r"^[0-9]+$", r"^[0-9a-fA-F]{8}-([0-9a-fA-F]{4}-){3}[0-9a-fA-F]{12}$")


def _located(text: Column, pattern: str, extra_group: int | None = None) -> Column:
    """array<struct<s, e, m>> of the pattern's matches in order; m: the match, or one of its groups."""
    gaps = F.transform(F.split(text, pattern, -1), F.length)
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    shown = found if extra_group is None else F.regexp_extract_all(text, F.lit(pattern), F.lit(extra_group))
    pieces = F.arrays_zip(gaps.alias("gap"), F.transform(found, F.length).alias("len"), shown.alias("m"))
    pieces = F.slice(pieces, F.lit(1), F.size(found))
    walked = F.aggregate(
        pieces,
        F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<s:int,e:int,m:string>>").alias("out")),
        lambda acc, x: F.struct(
            (acc["at"] + x["gap"] + x["len"]).alias("at"),
            F.concat(acc["out"], F.array(F.struct((acc["at"] + x["gap"]).alias("s"), (acc["at"] + x["gap"] + x["len"]).alias("e"), x["m"].alias("m")))).alias("out"),
        ),
        lambda acc: acc["out"],
    )
    return F.when(text.rlike(pattern), walked).otherwise(F.array().cast("array<struct<s:int,e:int,m:string>>"))


def _hot_range(string: Column, cls: CharClass) -> Column:
    """struct<first, last>: starts of the first and the last hot window of a string, -1 if there is none."""
    size, w = len(cls.alphabet), cls.width
    term = lambda c: F.when(c > 1, c * F.log2(c.cast("double"))).otherwise(F.lit(0.0))
    chars = F.transform(F.filter(F.split(string, ""), lambda c: c != ""), lambda c: F.call_function("locate", c, F.lit(cls.alphabet)))

    def step(acc: Column, x: Column) -> Column:
        # x: struct<i, into, out>; out is 0 while the first window fills
        gained = F.element_at(acc["n"], x["into"])
        one = F.transform(acc["n"], lambda c, j: c + F.when(j == x["into"] - 1, 1).otherwise(0))
        sum_in = acc["s"] - term(gained) + term(gained + 1)
        lost = F.element_at(one, F.greatest(x["out"], F.lit(1)))
        leaves = x["out"] > 0
        two = F.when(leaves, F.transform(one, lambda c, j: c - F.when(j == x["out"] - 1, 1).otherwise(0))).otherwise(one)
        total = F.when(leaves, sum_in - term(lost) + term(lost - 1)).otherwise(sum_in)
        hot = (x["i"] >= w - 1) & (F.log2(F.lit(float(w))) - total / F.lit(float(w)) >= F.lit(cls.bits))
        return F.struct(
            two.alias("n"),
            total.alias("s"),
            F.when(hot & (acc["first"] < 0), x["i"] - (w - 1)).otherwise(acc["first"]).alias("first"),
            F.when(hot, x["i"] - (w - 1)).otherwise(acc["last"]).alias("last"),
        )

    left = F.concat(F.array_repeat(F.lit(0), w), chars)
    moves = F.transform(F.arrays_zip(chars.alias("a"), F.slice(left, 1, F.size(chars)).alias("b")), lambda z, i: F.struct(i.alias("i"), z["a"].alias("into"), z["b"].alias("out")))
    start = F.struct(F.array_repeat(F.lit(0), size).alias("n"), F.lit(0.0).alias("s"), F.lit(-1).alias("first"), F.lit(-1).alias("last"))
    return F.aggregate(moves, start, step, lambda acc: F.struct(acc["first"], acc["last"]))


SPAN = "array<struct<s:int,o:int,e:int,kind:string>>"


def base_spans(text: Column) -> Column:
    """The fixed patterns' spans, by start and then kind."""
    kinds = ((ASSIGN, 2, ASSIGN_LEAST), (ACCESS, None, 0), (HEX, None, 0))
    arrays = []
    for order, (kind, (pattern, group, least)) in enumerate(zip(KINDS, kinds)):
        found = _located(text, pattern, group)
        if least:
            found = F.filter(found, lambda x: F.length(x["m"]) >= least)
        arrays.append(F.transform(found, lambda x: F.struct(x["s"].alias("s"), F.lit(order).alias("o"), x["e"].alias("e"), F.lit(kind).alias("kind"))))
    return F.array_sort(F.concat(*arrays))


def entropy_spans(text: Column, classes: tuple[CharClass, ...] = CLASSES, allow: tuple[str, ...] = ALLOW) -> Column:
    """Spans from the first to the last hot window of each candidate that is not on the allow list."""
    arrays = []
    for order, cls in enumerate(classes, start=len(KINDS)):
        found = _located(text, cls.pattern)
        for pattern in allow:
            found = F.filter(found, lambda x: ~x["m"].rlike(pattern))
        if cls.needs:
            found = F.filter(found, lambda x: x["m"].rlike(cls.needs))
        hot = F.transform(found, lambda x: F.struct(x["s"].alias("s"), _hot_range(x["m"], cls).alias("h")))
        hot = F.filter(hot, lambda x: x["h"]["first"] >= 0)
        arrays.append(F.transform(hot, lambda x: F.struct((x["s"] + x["h"]["first"]).alias("s"), F.lit(order).alias("o"), (x["s"] + x["h"]["last"] + cls.width).alias("e"), F.lit(cls.name).alias("kind"))))
    return F.concat(*arrays)


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", classes: tuple[CharClass, ...] = CLASSES, allow: tuple[str, ...] = ALLOW) -> DataFrame:
    """One row per row of docs: the id, ``base`` and ``found`` (all) as arrays of struct<s, o, e, kind>."""
    text = F.coalesce(F.col("_text"), F.lit(""))
    df = docs.select(F.col(id_col), F.col(text_col).cast("string").alias("_text"))
    df = df.select(id_col, base_spans(text).alias("base"), entropy_spans(text, classes, allow).alias("_more"))
    return df.select(id_col, "base", F.array_sort(F.concat("base", "_more")).alias("found"))


def joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["s"].cast("string"), x["e"].cast("string"))), ",")


def redact(docs: DataFrame, text_col: str = "text", mask: str = "[secret]", classes: tuple[CharClass, ...] = CLASSES, allow: tuple[str, ...] = ALLOW) -> DataFrame:
    """Replace every span, overlapping ones as one, by the mask; all columns stay, rows without spans are unchanged."""
    text = F.col(text_col)
    spans = F.array_sort(F.concat(base_spans(F.coalesce(text, F.lit(""))), entropy_spans(F.coalesce(text, F.lit("")), classes, allow)))
    marked = docs.withColumn("_spans", spans)
    built = F.aggregate(
        "_spans",
        F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out")),
        lambda acc, x: F.struct(
            F.greatest(acc["at"], x["e"]).alias("at"),
            F.when(x["s"] >= acc["at"], F.concat(acc["out"], F.array(F.substring(text, acc["at"] + 1, x["s"] - acc["at"]), F.lit(mask)))).otherwise(acc["out"]).alias("out"),
        ),
        lambda acc: F.concat(F.array_join(acc["out"], ""), F.substring(text, acc["at"] + 1, F.length(text))),
    )
    return marked.withColumn(text_col, F.when(F.size("_spans") > 0, built).otherwise(text)).drop("_spans")
