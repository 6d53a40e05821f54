"""Text-render stream: layout specifications, training rows with provenance, glyph cells."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Axes of a render and their settings; the rule for one row is ``pick``.
AXES: dict[str, tuple] = {
    "family": ("serif", "sans", "mono", "script", "display"),
    "weight": (300, 400, 600, 800),
    "kerning": (-0.05, 0.0, 0.1),
    "alignment": ("left", "centre", "right", "justify"),
    "colour": ("black", "white", "red", "blue", "green", "gold"),
    "opacity": (0.4, 0.7, 1.0),
    "shadow": (0, 1),
    "outline": (0, 1),
    "placement": ("top", "middle", "bottom", "corner"),
    "curvature": (0.0, 0.2, 0.5),
    "perspective": (0, 10, 25),
}
_STRIDE, _STEP, _RING = 7919, 104_729, 1_000_003
#: Sampling weight of each difficulty: short renders come more often.
WEIGHTS = {"word": 1.0, "line": 0.5, "paragraph": 0.25}


def pick(key: Column, axis: str) -> Column:
    """The setting of one axis for an integer key: spread over a prime ring, then over the settings."""
    values, at = AXES[axis], list(AXES).index(axis)
    place = F.pmod(F.pmod(key, F.lit(_RING)) * _STRIDE + at * _STEP, F.lit(_RING)) % len(values)
    return F.get(F.array(*map(F.lit, values)), place.cast("int"))


def pick_sql(key: str, axis: str) -> str:
    values, at = AXES[axis], list(AXES).index(axis)
    return f"[{', '.join(map(repr, values))}][((({key} % {_RING}) * {_STRIDE} + {at * _STEP}) % {_RING}) % {len(values)} + 1]"


def specs(df: DataFrame, key: str) -> DataFrame:
    """``key`` and one setting for every axis. Keys are not negative."""
    return df.select(key, *[pick(F.col(key), a).alias(a) for a in AXES])


def difficulty(text: Column) -> Column:
    words = F.size(F.split(F.trim(text), " "))
    return F.when(words == 1, "word").when(words <= 12, "line").otherwise("paragraph")


def script(text: Column) -> Column:
    """Stage of the script curriculum that a text belongs to: logographic, other alphabets, Latin with marks, Latin."""
    return F.when(text.rlike(r"[\p{IsHan}\p{IsHiragana}\p{IsKatakana}\p{IsHangul}]"), "logographic").when(text.rlike(r"[\p{IsCyrillic}\p{IsGreek}\p{IsArabic}\p{IsHebrew}\p{IsDevanagari}]"), "other_alphabet").when(text.rlike("[\u00C0-\u024F]"), "latin_extended").otherwise("latin")


def rows(df: DataFrame, key: str, text: str) -> DataFrame:
    """Training rows: the exact text as caption, where it comes from, and how often it is drawn."""
    level = difficulty(F.col(text))
    weight = F.element_at(F.create_map(*[F.lit(x) for kv in WEIGHTS.items() for x in kv]), level)
    return df.select(key, F.concat(F.lit("Text that reads: "), F.col(text)).alias("caption"), F.lit("text-render").alias("provenance"), level.alias("difficulty"), weight.alias("weight"), F.sha2(F.col(text), 256).alias("sha256"))


def cell(code: Column, i: Column) -> Column:
    """Whether cell i (row-major, 8 wide, 16 high) of a character's stand-in glyph has ink."""
    return (F.pmod(code * ((i % 8) + 1) * 31 + F.floor(i / 8) * 17 + (i % 8) * 7, F.lit(5)) == 0).cast("int")


def ink(text: Column) -> Column:
    """Cells with ink over a line of text."""
    one = lambda code: F.aggregate(F.sequence(F.lit(0), F.lit(127)), F.lit(0), lambda s, i: s + cell(code, i))
    return F.aggregate(F.transform(F.filter(F.split(text, ""), lambda c: c != ""), lambda c: one(F.ascii(c))), F.lit(0), lambda s, x: s + x)
