"""Column functions on identifiers and texts; built-in expressions only."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# Letters with marks and what they fold to.
MARKED = "áàâäãåéèêëíìîïóòôöõúùûüñçßýÿığşÁÀÂÄÃÅÉÈÊËÍÌÎÏÓÒÔÖÕÚÙÛÜÑÇİĞŞ"
PLAIN = "aaaaaaeeeeiiiiooooouuuuncsyyigsAAAAAAEEEEIIIIOOOOOUUUUNCIGS"
#: Names that no dialect takes unquoted; a guarded one gets a trailing mark.
RESERVED = ("select", "from", "where", "group", "order", "by", "having", "limit", "join", "on", "union", "all", "and", "or", "not", "null", "case", "when", "then", "else", "end", "as", "in", "is", "like")
TOKEN = r"[\p{L}\p{N}]+|[^\s\p{L}\p{N}]"
NUMBER = r"[0-9]+(?:[.,][0-9]+)*"


def to_ascii_snake(name: Column) -> Column:
    """ASCII lower snake case: marks folded, camel case split, separators squeezed, leading digits and reserved words guarded."""
    plain = F.translate(name, MARKED, PLAIN)
    split = F.regexp_replace(plain, "([a-z0-9])([A-Z])", "$1_$2")
    joined = F.trim(F.regexp_replace(F.lower(split), "[^a-z0-9]+", "_"), F.lit("_"))
    led = F.when(joined.rlike("^[0-9]"), F.concat(F.lit("n_"), joined)).otherwise(joined)
    return F.when(led.isin(*RESERVED), F.concat(led, F.lit("_"))).when(led == "", "unnamed").otherwise(led)


def subwords(name: Column) -> Column:
    """Parts of a snake-case name."""
    return F.filter(F.split(F.lower(name), "_"), lambda x: x != "")


def tokens(text: Column) -> Column:
    """Words and punctuation marks."""
    return F.regexp_extract_all(text, F.lit(TOKEN), F.lit(0))


def words(text: Column) -> Column:
    """Stretches between white space."""
    return F.filter(F.split(F.trim(text), r"\s+"), lambda x: x != "")


def numbers(text: Column) -> Column:
    return F.regexp_extract_all(text, F.lit(NUMBER), F.lit(0))


def spans(text: Column) -> Column:
    """Back-ticked spans: every second piece between back-ticks; a last unclosed one does not count."""
    pieces = F.split(text, "`", -1)
    closed = F.when(F.size(pieces) % 2 == 0, F.slice(pieces, 1, F.size(pieces) - 1)).otherwise(pieces)
    return F.filter(closed, lambda _, i: i % 2 == 1)


def backticks_balanced(text: Column) -> Column:
    return F.size(F.split(text, "`", -1)) % 2 == 1


def freeze(text: Column, pattern: str = NUMBER, mark: str = "⟦{}⟧") -> Column:
    """Struct of ``frozen`` (each match replaced by a numbered placeholder) and ``held`` (the matches in order)."""
    held = F.regexp_extract_all(text, F.lit(f"({pattern})"), F.lit(1))
    pieces = F.split(text, pattern, -1)
    left, right = mark.split("{}")
    joined = F.array_join(F.transform(pieces, lambda p, i: F.when(i == 0, p).otherwise(F.concat(F.lit(left), i.cast("string"), F.lit(right), p))), "")
    return F.struct(joined.alias("frozen"), held.alias("held"))


def thaw(frozen: Column, held: Column, mark: str = "⟦{}⟧") -> Column:
    """Put the held matches back for their placeholders."""
    left, right = mark.split("{}")
    pieces = F.split(frozen, f"{left}[0-9]+{right}", -1)
    return F.array_join(F.transform(pieces, lambda p, i: F.when(i == 0, p).otherwise(F.concat(F.get(held, i - 1), p))), "")


def constants(text: Column) -> Column:
    """Sorted numbers, quoted values and back-ticked spans of a text."""
    quoted = F.regexp_extract_all(text, F.lit("'([^']*)'"), F.lit(1))
    return F.array_sort(F.concat(numbers(F.regexp_replace(text, "'[^']*'|`[^`]*`", " ")), quoted, spans(text)))


def constants_preserved(before: Column, after: Column) -> Column:
    return constants(before) == constants(after)
