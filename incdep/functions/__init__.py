"""Column expressions: canonical tokens, fingerprints, combined hashes, sketch registers."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

LONG_TOKEN = 64


def token(col: Column, nulls: str = "equal", compact: bool = True) -> Column:
    """Canonical text of a value with a tag, so that NULL (its own value) differs from any text.

    ``nulls="ignore"`` leaves NULL as NULL. ``compact`` replaces text longer than ``LONG_TOKEN`` by its SHA-256 digest,
    under another tag: equality stays, and long text is never shuffled.
    """
    text = col.cast("string")
    body = F.concat(F.lit("v"), text)
    if compact:
        body = F.when(F.length(text) > LONG_TOKEN, F.concat(F.lit("x"), F.sha2(text.cast("binary"), 256))).otherwise(body)
    return F.coalesce(body, F.lit("n")) if nulls == "equal" else body


def quoted(name: str) -> str:
    return "`" + name.replace("`", "``") + "`"


def token_sql(column: str, nulls: str = "equal", compact: bool = True) -> str:
    """``token`` of a named column as SQL text: a wide table's tokens are then one call to the JVM, not a dozen a column."""
    text = f"cast({column} as string)"
    body = f"concat('v', {text})"
    if compact:
        body = f"case when length({text}) > {LONG_TOKEN} then concat('x', sha2(cast({text} as binary), 256)) else {body} end"
    return f"coalesce({body}, 'n')" if nulls == "equal" else body


def fingerprint_sql(tok: str, fn: str = "xx", seed: int | None = None) -> str:
    """``fingerprint`` as SQL text; NULL for a NULL token. ``seed`` makes another hash."""
    if fn not in ("xx", "md5"):
        raise ValueError(f"fn={fn!r}")
    h = f"cast(conv(substring(md5(cast({tok} as binary)), 1, 15), 16, 10) as bigint)" if fn == "md5" else f"xxhash64({'' if seed is None else f'{seed}, '}{tok})"
    return f"case when {tok} is not null then {h} end"


def row_token(tokens: list[Column]) -> Column:
    """One text for a tuple of tokens; lengths keep it unambiguous. NULL if any token is NULL."""
    if len(tokens) == 1:
        return tokens[0]
    return F.concat(*(part for t in tokens for part in (F.length(t).cast("string"), F.lit(":"), t)))


def fingerprint(tok: Column, fn: str = "xx") -> Column:
    """64-bit hash of a token (``xx``), or the 60 bits of an md5 digest's first 15 hex digits, as other engines can compute them."""
    if fn == "xx":
        return F.xxhash64(tok)
    if fn == "md5":
        return F.conv(F.substring(F.md5(tok.cast("binary")), 1, 15), 16, 10).cast("long")
    raise ValueError(f"fn={fn!r}")


def rotate(h: Column, width: int = 64) -> Column:
    """Rotate left by one bit inside ``width`` bits."""
    if width == 64:
        return F.shiftleft(h, 1).bitwiseOR(F.shiftrightunsigned(h, 63))
    low = F.lit((1 << (width - 1)) - 1)
    return F.shiftleft(h.bitwiseAND(low), 1).bitwiseOR(F.shiftrightunsigned(h, width - 1))


def fold(hashes: list[Column], width: int = 64) -> Column:
    """Order-sensitive hash of a tuple from its values' hashes; a single hash stays as it is."""
    return reduce(lambda acc, h: rotate(acc, width).bitwiseXOR(h), hashes[1:], hashes[0])


def folded(df: DataFrame, combos: Sequence[Sequence[str]], width: int = 64) -> tuple[DataFrame, list[str]]:
    """``df`` with the combined hash of each combination of its hash columns, and the names of these columns.

    One projection for each place in a combination: a combined hash is computed from the one of its prefix, which combinations share,
    so expressions grow with the number of prefixes and not, as a rotated value is used twice, with the power of their length.
    """
    names: dict[tuple[str, ...], str] = {(c,): c for combo in combos for c in combo}
    for j in range(2, max(map(len, combos), default=1) + 1):
        fresh = list(dict.fromkeys(tuple(c[:j]) for c in combos if len(c) >= j))
        later = {x for c in combos for x in c[j:]} | {names[tuple(c)] for c in combos if len(c) < j}
        new = {prefix: f"p{j}_{k}" for k, prefix in enumerate(fresh)}
        turned = lambda x: f"(shiftleft({x} & {(1 << (width - 1)) - 1}L, 1) | shiftrightunsigned({x}, {width - 1}))"
        df = df.selectExpr(*sorted(later), *(f"{turned(names[prefix[:-1]])} ^ {prefix[-1]} as {name}" for prefix, name in new.items()))
        names |= new
    return df, [names[tuple(c)] for c in combos]


def bucket(h: Column, lgk: int) -> Column:
    """Register number: the low ``lgk`` bits."""
    return h.bitwiseAND(F.lit((1 << lgk) - 1)).cast("int")


def rho(h: Column, lgk: int, width: int = 64) -> Column:
    """Position of the lowest set bit above the register number's bits, from 1."""
    x = F.shiftrightunsigned(h, lgk)
    return F.when(x == 0, F.lit(width - lgk + 1)).otherwise(F.bit_count(x.bitwiseAND(-x) - 1) + 1).cast("int")


def word_masks(member: Column, n: int) -> list[Column]:
    """Aggregates that OR together 64-bit words in which bit ``member`` of ``n`` is set."""
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), (member % 64).cast("int"))
    return [F.bit_or(F.when(F.floor(member / 64) == w, bit).otherwise(F.lit(0).cast("long"))).alias(f"w{w}") for w in range(max(1, -(-n // 64)))]


def has_bit(words: list[str], member: Column) -> Column:
    """Whether bit ``member`` is set in the words of a row."""
    word = F.element_at(F.array(*words), (F.floor(member / 64) + 1).cast("int")) if len(words) > 1 else F.col(words[0])
    return F.call_function("getbit", word, (member % 64).cast("int")) == 1
