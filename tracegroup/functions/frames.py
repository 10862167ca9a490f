"""Frames of a stack trace: parts of a qualified name, pieces of an identifier, fingerprints of a trace."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SEPARATOR = "\u0001"


def parse_frame(frame: Column, sep: str | None = ".") -> Column:
    """struct(package, class_name, method). Fewer parts fill from the right; sep=None puts the whole frame into method."""
    if sep is None:
        return F.struct(F.lit("").alias("package"), F.lit("").alias("class_name"), frame.alias("method"))
    parts = F.split(frame, "".join(f"\\{c}" for c in sep))
    n = F.size(parts)
    part = lambda back: F.when(n >= back, F.element_at(parts, -back)).otherwise("")
    package = F.when(n > 2, F.array_join(F.slice(parts, 1, F.greatest(n - 2, F.lit(1))), sep)).otherwise("")
    return F.struct(package.alias("package"), part(2).alias("class_name"), part(1).alias("method"))


def split_camel(name: Column, lower: bool = True) -> Column:
    """Pieces of a camelCase name: words, acronym runs, digit runs; other signs separate."""
    out = F.regexp_replace(name, r"([\p{Ll}\p{Nd}])(\p{Lu})", "$1 $2")
    out = F.regexp_replace(out, r"(\p{Lu})(\p{Lu}\p{Ll})", "$1 $2")
    out = F.regexp_replace(out, r"(\p{L})(\p{Nd})", "$1 $2")
    out = F.regexp_replace(out, r"(\p{Nd})(\p{L})", "$1 $2")
    pieces = F.filter(F.split(out, r"[^\p{L}\p{Nd}]+"), lambda x: x != "")
    return F.transform(pieces, F.lower) if lower else pieces


def split_snake(name: Column, lower: bool = True) -> Column:
    """Pieces of a snake_case name: what stands between underscores and other signs."""
    pieces = F.filter(F.split(name, r"[^\p{L}\p{Nd}]+"), lambda x: x != "")
    return F.transform(pieces, F.lower) if lower else pieces


SPLITTERS = {"camel": split_camel, "snake": split_snake, "none": lambda name, lower=True: F.filter(F.array(F.lower(name) if lower else name), lambda x: x != "")}


def pieces(frame: Column, style: str = "camel", split_parts: str = "all", sep: str | None = ".") -> Column:
    """All pieces of a frame in order of its parts. split_parts='package' leaves class and method whole."""
    parsed = parse_frame(frame, sep)
    cut, whole = SPLITTERS[style], SPLITTERS["none"]
    rest = cut if split_parts == "all" else whole
    return F.concat(cut(parsed["package"]), rest(parsed["class_name"]), rest(parsed["method"]))


def from_text(text: Column) -> Column:
    """Frames of a printed trace, one per line: `at a.b.C.m(File:12)` and lines like `#3 0x1f in ns::f () from lib` ; others are left out."""
    lines = F.split(text, r"\r?\n")
    java = lambda x: F.regexp_extract(x, r"^\s*at\s+([^\s(]+)", 1)
    native = lambda x: F.regexp_extract(x, r"^\s*#\d+\s+(?:0x[0-9a-fA-F]+\s+in\s+)?([^\s(]+)", 1)
    return F.filter(F.transform(lines, lambda x: F.when(java(x) != "", java(x)).otherwise(native(x))), lambda x: x != "")


def normalise(frame: Column) -> Column:
    """Without line numbers, addresses and generated suffixes of lambdas, trimmed."""
    out = F.regexp_replace(frame, r"\(.*\)$", "")
    out = F.regexp_replace(out, r"\$\$Lambda.*$|\$\d+|0x[0-9a-fA-F]+", "")
    return F.trim(out)


def collapse_recursion(frames: Column) -> Column:
    """Equal frames that follow each other count once."""
    step = F.aggregate(frames, F.array().cast("array<string>"), lambda acc, x: F.when((F.size(acc) > 0) & (F.try_element_at(acc, F.lit(-1)) == x), acc).otherwise(F.concat(acc, F.array(x))))
    return step


def top(frames: Column, n: int) -> Column:
    """The n frames nearest to the failure."""
    return F.slice(frames, 1, n)


def fingerprint(frames: Column) -> Column:
    """sha256 of the frame sequence: identical traces, and no others, have the same."""
    return F.sha2(F.concat_ws(SEPARATOR, frames), 256)


def concatenated(frames: Column, delimiter: str = "\n", most_frames: int | None = None) -> Column:
    """The text that a text-embedding model is given: the frames joined by a delimiter, cut to the first most_frames."""
    return F.array_join(F.slice(frames, 1, most_frames) if most_frames else frames, delimiter)
