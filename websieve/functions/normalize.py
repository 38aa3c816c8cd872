"""The normal form under which paragraphs are compared, and the 64-bit key of it.

Lower case, accents off, numbers masked, punctuation off, in this order; every step is a built-in
expression, so the whole form stays inside generated code.
"""

from __future__ import annotations

import unicodedata
from dataclasses import dataclass
from functools import cache

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class NormOptions:
    lower: bool = True
    accents: bool = True
    digits: str = "run"  # "run": a number becomes one 0; "each": every digit does; "" leaves them
    punct: bool = True


@cache
def accent_map() -> tuple[str, str]:
    """Letters of the first plane that decompose to a letter and marks, and those letters."""
    accented, plain = [], []
    for code in range(0xC0, 0xFFFF):
        parts = unicodedata.normalize("NFD", chr(code))
        if len(parts) > 1 and all(unicodedata.category(p) == "Mn" for p in parts[1:]):
            accented.append(chr(code))
            plain.append(parts[0])
    return "".join(accented), "".join(plain)


def strip_accents(text: Column) -> Column:
    return F.regexp_replace(F.translate(text, *accent_map()), r"\p{Mn}+", "")


def mask_numbers(text: Column, mode: str = "run") -> Column:
    return F.regexp_replace(text, r"\p{Nd}+" if mode == "run" else r"\p{Nd}", "0")


def strip_punct(text: Column) -> Column:
    return F.regexp_replace(text, r"\p{P}+", "")


def normalize(text: Column, opts: NormOptions = NormOptions()) -> Column:
    text = F.lower(text) if opts.lower else text
    text = strip_accents(text) if opts.accents else text
    text = mask_numbers(text, opts.digits) if opts.digits else text
    return strip_punct(text) if opts.punct else text


def key64(normal: Column, form: str = "hex") -> Column:
    """The first 64 bits of the SHA-1 of a normal form: 16 hexadecimal digits, or the same bits as a long."""
    digits = F.substring(F.sha1(F.encode(normal, "UTF-8")), 1, 16)
    if form == "hex":
        return digits
    # conv() yields the unsigned number, beyond a long for half of the keys; two halves stay inside.
    high, low = (F.conv(F.substring(digits, at, 8), 16, 10).cast("long") for at in (1, 9))
    return F.shiftleft(high, 32).bitwiseOR(low)
