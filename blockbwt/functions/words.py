"""Symbol words: suffixes as fixed numbers of packed symbols in 62-bit words.

Each string is packed once, at its own word boundaries; a suffix's word is two
neighbours shifted together. With 2 bits a symbol (alphabets of four) padding
looks like the first symbol, so the suffix's length breaks ties; with one code
more, 0 is the end marker and no length is needed. All of it is expressions.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

WORD_BITS = 62
#: Words carried as columns; the rest of a long suffix's words is one array.
COLUMNS = 4
_DIGITS = "0123456789abcdefghijklmnopqrstuvwxyz"


class Packing:
    def __init__(self, alphabet: tuple[str, ...], encoding: str = "auto", word_bits: int = WORD_BITS):
        if encoding == "auto":
            encoding = "bits" if len(alphabet) <= 4 else "radix"
        if encoding not in ("bits", "radix"):
            raise ValueError(encoding)
        self.alphabet, self.encoding = alphabet, encoding
        codes = len(alphabet) + (encoding == "radix")
        self.bits = max(1, math.ceil(math.log2(max(2, codes))))
        self.symbols = word_bits // self.bits
        self.used = self.symbols * self.bits
        self.first = int(encoding == "radix")

    @property
    def needs_length(self) -> bool:
        return self.encoding == "bits"

    def words(self, longest: int) -> int:
        return max(1, -(-longest // self.symbols))

    def packed(self, s: Column) -> Column:
        """The string's words, and two of zeros after its last, so that a neighbour is always there."""
        k, chars = self.symbols, "".join(self.alphabet)
        if self.bits <= 5:
            digits = F.rpad(F.translate(s, chars, _DIGITS[self.first : self.first + len(chars)]), (F.ceil(F.length(s) / k) * k).cast("int"), F.lit("0"))
            word = lambda i: F.conv(F.substring(digits, i * k + 1, F.lit(k)), 1 << self.bits, 10).cast("long")
        else:
            code = F.transform(F.split(s, ""), lambda c: F.instr(F.lit(chars), c).cast("long") - 1 + self.first)
            full = F.concat(F.filter(code, lambda c: c >= self.first), F.array_repeat(F.lit(0).cast("long"), k))
            word = lambda i: F.aggregate(F.slice(full, i * k + 1, F.lit(k)), F.lit(0).cast("long"), lambda a, c: F.shiftleft(a, self.bits).bitwiseOR(c))
        n = F.ceil(F.length(s) / k).cast("int")
        some = F.when(n > 0, F.transform(F.sequence(F.lit(0), n - 1), word)).otherwise(F.array().cast("array<bigint>"))
        return F.concat(some, F.array(F.lit(0).cast("long"), F.lit(0).cast("long")))

    def word(self, packed: Column, pos: Column, j: int | Column) -> Column:
        """Word j of the suffix at pos: two neighbours, shifted together and masked."""
        k = self.symbols
        at = F.floor(pos / k).cast("int") + (j if isinstance(j, Column) else F.lit(j)) + 1
        off = (pos % k) * self.bits
        a, b = (F.coalesce(F.get(packed, at - 1 + i), F.lit(0).cast("long")) for i in (0, 1))
        mask = F.lit((1 << self.used) - 1).cast("long")
        return F.call_function("shiftleft", a, off.cast("int")).bitwiseAND(mask).bitwiseOR(F.call_function("shiftrightunsigned", b, (F.lit(self.used) - off).cast("int")))

    def bucket(self, depth: int, word: Column, left: Column) -> Column:
        """The bucket of a suffix by its first `depth` symbols, as a number: from its first word, and where padding looks like a symbol its length up to that."""
        if depth > self.symbols - 4:
            raise ValueError("a bucket's symbols have to fit a word")
        code = F.shiftrightunsigned(word, self.used - depth * self.bits)
        return code * (depth + 1) + F.least(left, F.lit(depth)) if self.needs_length else code

    def bucket_of(self, bucket: Column, depth: int) -> Column:
        """The same number of a padded prefix."""
        chars = "".join(self.alphabet)
        body = F.replace(bucket, F.lit("\0"), F.lit(""))
        if self.bits <= 5:
            code = F.conv(F.rpad(F.translate(body, chars, _DIGITS[self.first : self.first + len(chars)]), depth, "0"), 1 << self.bits, 10).cast("long")
        else:
            each = F.transform(F.split(F.rpad(body, depth, "\0"), ""), lambda c: F.greatest(F.instr(F.lit(chars), c).cast("long") - 1 + self.first, F.lit(0).cast("long")))
            code = F.aggregate(F.slice(each, 1, depth), F.lit(0).cast("long"), lambda a, c: F.shiftleft(a, self.bits).bitwiseOR(c))
        return code * (depth + 1) + F.length(body) if self.needs_length else code

    def fits(self, depth: int) -> bool:
        return depth <= self.symbols - 4

    def keys(self, packed: Column, pos: Column, longest: int, left: Column, begin: int = 0, count: int | None = None) -> list[Column]:
        """Sort keys of a suffix from word `begin` on; left: its length."""
        n = self.words(longest) - begin if count is None else count
        out = [self.word(packed, pos, begin + j).alias(f"w{j}") for j in range(min(n, COLUMNS))]
        if n > COLUMNS:
            rest = F.transform(F.sequence(F.lit(begin + COLUMNS), F.lit(begin + n - 1)), lambda j: self.word(packed, pos, j))
            out.append(rest.alias("wr"))
        if self.needs_length:
            out.append(left.cast("int").alias("wl"))
        return out


def digit_words(s: Column, alphabet: tuple[str, ...], pos: Column, begin: int, symbols: int) -> Column:
    """Symbols of a suffix as one (sigma + 1)-ary integer, packed anew for each suffix; for checks of the shifted words."""
    chars, base = "".join(alphabet), len(alphabet) + 1
    part = F.rpad(F.substring(s, pos + 1 + begin, F.lit(symbols)), symbols, F.lit("\0"))
    return F.conv(F.translate(part, "\0" + chars, _DIGITS[:base]), base, 10).cast("long")


def digit_keys(s: Column, alphabet: tuple[str, ...], pos: Column, longest: int) -> list[Column]:
    """Sort keys of a suffix as (sigma + 1)-ary integers, padding being 0: more symbols a word than whole bits hold, each packed anew."""
    if len(alphabet) >= len(_DIGITS):
        raise ValueError("an alphabet of at most 35 symbols")
    k = int(62 / math.log2(max(2, len(alphabet) + 1)))
    n = max(1, -(-longest // k))
    out = [digit_words(s, alphabet, pos, j * k, k).alias(f"w{j}") for j in range(min(n, COLUMNS))]
    if n > COLUMNS:
        out.append(F.array(*[digit_words(s, alphabet, pos, j * k, k) for j in range(COLUMNS, n)]).alias("wr"))
    return out


def utf8_key(s: Column, pos: Column) -> Column:
    """The suffix as bytes, which compare unsigned: for alphabets of any size."""
    return F.encode(F.substring(s, pos + 1, F.length(s)), "utf-8")
