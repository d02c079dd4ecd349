"""Text functions as Column expressions. All are narrow; only nfc() and repair of mixed damage may leave the JVM."""

from __future__ import annotations

import unicodedata

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

WHITE = "[ \\t\\n\\r\\f\\x0B]+"
# fixed values: the characters that windows-1252 puts at 0x80 to 0x9F, and those places
_PUNCTUATION_1252 = "€‚ƒ„…†‡ˆ‰Š‹ŒŽ‘’“”•–—˜™š›œžŸ"
_PLACES_1252 = "\x80\x82\x83\x84\x85\x86\x87\x88\x89\x8a\x8b\x8c\x8e\x91\x92\x93\x94\x95\x96\x97\x98\x99\x9a\x9b\x9c\x9e\x9f"
# fixed values: character references that are decoded; the ampersand comes last so that none is decoded twice
ENTITIES = (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&apos;", "'"), ("&nbsp;", "\xa0"), ("&copy;", "©"), ("&middot;", "·"), ("&amp;", "&"))


def collapse_ws(c: Column) -> Column:
    return F.trim(F.regexp_replace(c, WHITE, " "))


def collapse_runs(c: Column, keep: int = 3) -> Column:
    """Runs of more than `keep` equal characters become `keep` of them."""
    return F.regexp_replace(c, "(?s)(.)\\1{%d,}" % keep, "$1" * keep)


def word_count(c: Column) -> Column:
    """Words of text whose white space is collapsed."""
    return F.when(c == "", 0).otherwise(F.size(F.split(c, " "))).cast("long")


def content_key(c: Column, mode: str = "normalized") -> Column:
    """SHA-256, as hexadecimal digits, of the text or of its lower-cased, white-space-collapsed form."""
    if mode == "raw":
        return F.sha2(c, 256)
    if mode != "normalized":
        raise ValueError(f"mode is raw or normalized, not {mode}")
    return F.sha2(collapse_ws(F.lower(c)), 256)


#: A lead byte and a continuation byte, both misread as characters; windows-1252 shows some of the latter as punctuation.
_MISREAD = f"[\\xC2-\\xF4][\\x80-\\xBF{_PUNCTUATION_1252}]"


def suspicious(c: Column) -> Column:
    """A lead byte followed by a continuation byte, both misread as characters."""
    return c.rlike(_MISREAD)


def _mended(c: Column, passes: int) -> Column:
    """c, a column or lambda variable, with up to `passes` misreadings undone. A pass that can't be taken ends it."""
    def reread(plain: Column) -> Column:
        # the guard stands inside the argument: encode() raises on what the charset lacks
        return F.encode(F.when(~plain.rlike("[^\\x00-\\xFF]"), plain), "ISO-8859-1").cast("string")

    def judged(again: Column) -> Column:
        return F.when(F.is_valid_utf8(again), _mended(again, passes - 1) if passes > 1 else again).otherwise(c)

    read = bound(F.translate(c, _PUNCTUATION_1252, _PLACES_1252), reread)
    return F.when(suspicious(c), bound(read, judged)).otherwise(c)


def _segments(text: str | None, passes: int) -> str | None:
    """Repair runs of characters that hold misread bytes, where the whole text can't be one misread string."""
    import re

    if text is None:
        return None
    places = str.maketrans(_PUNCTUATION_1252, _PLACES_1252)
    for _ in range(passes):
        def mend(m: re.Match) -> str:
            try:
                return m[0].translate(places).encode("latin-1").decode()
            except UnicodeError:
                return m[0]

        # a lead byte and as many continuation bytes as it announces
        cont = f"[\x80-\xbf{_PUNCTUATION_1252}]"
        now = re.sub(f"[\xc2-\xdf]{cont}|[\xe0-\xef]{cont}{{2}}|[\xf0-\xf4]{cont}{{3}}", mend, text)
        if now == text:
            break
        text = now
    return text


def repair_mojibake(c: Column, passes: int = 2) -> Column:
    """Undo UTF-8 read as Latin-1 or windows-1252, up to `passes` times over.

    A pass is taken only if the text shows a misread pair and its bytes are valid UTF-8.
    """
    return bound(c, lambda t: _mended(t, passes)) if passes > 0 else c


def repair_mixed(df: DataFrame, column: str, to: str, passes: int = 2) -> DataFrame:
    """df with `to`, the column repaired where the whole text or only a part of it is misread; parts in Python, for
    texts that still look misread alone."""
    whole = computed(df, __whole=repair_mojibake(F.col(column), passes))
    asked = computed(whole, __asked=F.when(suspicious(F.col("__whole")), F.col("__whole")))

    @F.arrow_udf(StringType())
    def mend(texts: pa.Array) -> pa.Array:
        return pa.array([_segments(t, passes) for t in texts.to_pylist()], pa.string())

    return asked.withColumn(to, F.coalesce(mend("__asked"), "__whole")).drop("__whole", "__asked")


@F.arrow_udf(StringType())
def _nfc(texts: pa.Array) -> pa.Array:
    # Arrow's own normaliser leaves marks apart in its composed forms
    return pa.array([None if t is None else unicodedata.normalize("NFC", t) for t in texts.to_pylist()], pa.string())


def nfc(c: Column) -> Column:
    """Canonical composition. Text wholly below U+0300 is composed already and stays in the JVM."""
    guarded = c.rlike("[^\\u0000-\\u02FF]")
    return F.when(guarded, _nfc(F.when(guarded, c))).otherwise(c)


def nfc_column(df: DataFrame, column: str, to: str) -> DataFrame:
    """df with `to`, the canonical composition of a column that is named once."""
    asked = computed(df, __apart=F.when(F.col(column).rlike("[^\\u0000-\\u02FF]"), F.col(column)))
    return asked.withColumn(to, F.when(F.col("__apart").isNotNull(), _nfc("__apart")).otherwise(F.col(column))).drop("__apart")


def decode_entities(c: Column) -> Column:
    for name, sign in ENTITIES:  # one search each, c is named once
        c = F.replace(c, F.lit(name), F.lit(sign))
    return c


def drop_controls(c: Column) -> Column:
    """Control characters but tab, line feed and carriage return, the byte order mark, and terminal escapes go."""
    plain = F.regexp_replace(c, "\\x1B\\[[0-9;]*[A-Za-z]", "")
    return F.regexp_replace(plain, "[\\x00-\\x08\\x0B\\x0C\\x0E-\\x1F\\x7F\\uFEFF]", "")


def unify_lines(c: Column) -> Column:
    return F.regexp_replace(c, "\\r\\n|\\r|\\u2028|\\u2029|\\x85", "\n")


def straighten_quotes(c: Column) -> Column:
    return F.translate(c, "‘’‚‛“”„‟", "''''\"\"\"\"")


def split_ligatures(c: Column) -> Column:
    for sign, letters in (("ﬀ", "ff"), ("ﬁ", "fi"), ("ﬂ", "fl"), ("ﬃ", "ffi"), ("ﬄ", "ffl"), ("ﬅ", "st"), ("ﬆ", "st")):
        c = F.replace(c, F.lit(sign), F.lit(letters))
    return c


def narrow_width(c: Column) -> Column:
    """Full-width forms of ASCII, and the ideographic space, become ASCII."""
    wide = "".join(chr(x) for x in range(0xFF01, 0xFF5F)) + "　"
    return F.translate(c, wide, "".join(chr(x) for x in range(0x21, 0x7F)) + " ")


FIXES = {
    "mojibake": repair_mojibake,
    "entities": decode_entities,
    "controls": drop_controls,
    "lines": unify_lines,
    "quotes": straighten_quotes,
    "ligatures": split_ligatures,
    "width": narrow_width,
}


def fix_text(c: Column, parts: tuple[str, ...] = ("mojibake", "entities", "controls", "lines")) -> Column:
    for p in parts:
        c = FIXES[p](c)
    return c


def page_text(html: Column) -> Column:
    """The text of a page: script, style and comment blocks and tags go, character references are decoded."""
    bare = F.regexp_replace(html, "(?is)<(script|style)\\b[^>]*>.*?</(script|style)\\s*>|<!--.*?-->", " ")
    return collapse_ws(decode_entities(F.regexp_replace(bare, "(?s)<[^>]*>", " ")))


def bound(c: Column, then) -> Column:
    """then(c) with c evaluated once: an expression inside a lambda is otherwise evaluated for each element."""
    return F.get(F.transform(F.array(c), then), F.lit(0))


def computed(df: DataFrame, **columns: Column) -> DataFrame:
    """df with columns that are evaluated once, however often they are used after: the optimizer neither merges a
    generator into what reads it nor moves filters on its output below it."""
    return df.select("*", F.inline_outer(F.array(F.struct(*(c.alias(n) for n, c in columns.items())))))


def char_gram_bag(c: Column, n: int) -> Column:
    """Character n-grams in order, repeats included; shorter text has none. Linear in the text: substring() by place is not."""
    def grams(chars: Column) -> Column:
        at = F.sequence(F.lit(0), F.greatest(F.size(chars) - n, F.lit(0)))
        made = F.transform(at, lambda i: F.concat(*(F.get(chars, i + j) for j in range(n))))
        return F.when(F.size(chars) >= n, made).otherwise(F.array().cast("array<string>"))

    return bound(F.split(c, ""), grams)


def char_grams(c: Column, n: int) -> Column:
    """Distinct character n-grams."""
    return F.array_distinct(char_gram_bag(c, n))


def word_grams(c: Column, n: int) -> Column:
    """Distinct word n-grams of text whose white space is collapsed; fewer words have none."""
    def grams(words: Column) -> Column:
        at = F.sequence(F.lit(1), F.greatest(F.size(words) - (n - 1), F.lit(1)))
        made = F.array_distinct(F.transform(at, lambda i: F.concat_ws(" ", F.slice(words, i, n))))
        return F.when(F.size(words) >= n, made).otherwise(F.array().cast("array<string>"))

    return bound(F.split(c, " "), grams)
