"""External identifiers, and the engine's own (eid): kind/prefix+number, for example br/0601."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from biblake.functions.text import norm_hyphen, norm_space, once

# Kinds of entities that get an eid, and the shape of a prefix (06, digits without zero, 0).
KINDS = ("br", "ra", "ar", "re", "id")
PREFIX = "06[1-9]*0"
EID = f"^(br|ra|ar|re|id)/({PREFIX})([1-9][0-9]*)$"


def parse_eid(c: Column) -> Column:
    """(kind, prefix, num), null where the text is no eid. A prefix has no zero inside, so the split is unique."""
    part = lambda i: F.regexp_extract(c, EID, i)
    return F.when(c.rlike(EID), F.struct(part(1).alias("kind"), part(2).alias("prefix"), part(3).cast("decimal(20,0)").alias("num")))


def is_prefix(c: Column) -> Column:
    return c.rlike(f"^{PREFIX}$")


def make_eid(kind: str | Column, prefix: Column, num: Column) -> Column:
    return F.concat(F.lit(kind) if isinstance(kind, str) else kind, F.lit("/"), prefix, num.cast("string"))


def prefix_word(i: int) -> str:
    """The prefix of shard i: 060, 0610 to 0690, 06110 and on, counting with the digits 1 to 9."""
    digits = ""
    while i:
        i, d = divmod(i - 1, 9)
        digits = str(d + 1) + digits
    return f"06{digits}0"


def prefix_of_shard(c: Column, shards: int) -> Column:
    return F.element_at(F.array(*[F.lit(prefix_word(i)) for i in range(shards)]), (c + 1).cast("int"))


def eid_url(c: Column, base: str) -> Column:
    return F.concat(F.lit(base.rstrip("/") + "/"), c)


def url_eid(c: Column, base: str) -> Column:
    start = base.rstrip("/") + "/"
    return F.when(c.startswith(start), F.substr(c, F.lit(len(start) + 1)))


def supplier_of(df: DataFrame, eid: str, prefixes: DataFrame) -> DataFrame:
    """Adds ``supplier``: this store for the range of prefixes 06..0, else by a list (prefix, supplier) of other databases."""
    found = df.withColumn("_p", F.regexp_extract(F.col(eid), "^[a-z]+/(0[1-9]*0)", 1))
    listed = F.broadcast(prefixes.select(F.col("prefix").alias("_p"), F.col("supplier").alias("_s")))
    return found.join(listed, "_p", "left").withColumn("supplier", F.when(is_prefix(F.col("_p")), F.lit("this")).otherwise(F.col("_s"))).drop("_p", "_s")


def _digit(c: Column, i: int) -> Column:
    x = F.substr(c, F.lit(i), F.lit(1))
    return F.when(x == "X", 10).otherwise(x.try_cast("int"))


def _weighted(c: Column, weights: list[int]) -> Column:
    total = F.lit(0)
    for i, w in enumerate(weights, 1):
        total = total + _digit(c, i) * w
    return total


def _bare(c: Column) -> Column:
    return F.upper(F.regexp_replace(norm_hyphen(norm_space(c)), "[- ]", ""))


def valid_issn(c: Column) -> Column:
    return once(_bare(c), lambda x: F.coalesce(x.rlike("^\\d{7}[\\dX]$") & (_weighted(x, [8, 7, 6, 5, 4, 3, 2, 1]) % 11 == 0), F.lit(False)))


def valid_isbn(c: Column) -> Column:
    def ok(x: Column) -> Column:
        ten = x.rlike("^\\d{9}[\\dX]$") & (_weighted(x, list(range(10, 0, -1))) % 11 == 0)
        thirteen = x.rlike("^\\d{13}$") & (_weighted(x, [1, 3] * 6 + [1]) % 10 == 0)
        return F.coalesce(ten | thirteen, F.lit(False))

    return once(_bare(c), ok)


def issn_check(c: Column) -> Column:
    """The check character for the first seven digits."""
    rest = lambda x: (11 - _weighted(x, [8, 7, 6, 5, 4, 3, 2]) % 11) % 11
    return once(once(c, rest), lambda r: F.when(r == 10, "X").otherwise(r.cast("string")))


def orcid_check(c: Column) -> Column:
    """The check character for the first fifteen digits: powers of two modulo eleven."""
    rest = lambda x: (12 - _weighted(x, [1 << (16 - i) for i in range(1, 16)]).cast("bigint") % 11) % 11
    return once(once(c, rest), lambda r: F.when(r == 10, "X").otherwise(r.cast("string")))


def valid_orcid(c: Column) -> Column:
    def ok(x: Column) -> Column:
        return F.coalesce(x.rlike("^\\d{15}[\\dX]$") & (orcid_check(x) == F.substr(x, F.lit(16), F.lit(1))), F.lit(False))

    return once(_bare(F.regexp_replace(c, "^https?://orcid\\.org/", "")), ok)


def norm_doi(c: Column) -> Column:
    return F.regexp_replace(F.lower(F.btrim(norm_hyphen(norm_space(c)))), "^(https?://(dx\\.)?doi\\.org/|doi:\\s*)", "")


def valid_doi(c: Column) -> Column:
    return F.coalesce(norm_doi(c).rlike("^10\\.\\d{4,9}/\\S+$"), F.lit(False))


def valid_pmid(c: Column) -> Column:
    return F.coalesce(c.rlike("^[1-9]\\d*$"), F.lit(False))


def norm_url(c: Column) -> Column:
    """Lower-case scheme and host, no query, fragment or last slash."""
    bare = F.regexp_replace(F.btrim(c), "[?#].*$", "")
    head = F.regexp_extract(bare, "^([A-Za-z][A-Za-z0-9+.-]*://[^/]*)", 1)
    return F.regexp_replace(F.concat(F.lower(head), F.substr(bare, F.char_length(head) + 1)), "/+$", "")


def norm_id(scheme: Column, value: Column) -> Column:
    """The form under which an identifier is a key."""
    v = F.btrim(norm_hyphen(norm_space(value)))
    return F.when(scheme == "doi", norm_doi(v)).when(scheme.isin("issn", "isbn", "orcid"), F.upper(v)).when(scheme == "url", norm_url(v)).otherwise(v)


def valid_id(scheme: Column, value: Column) -> Column:
    """Checked by scheme; other schemes only need a value."""
    return (
        F.when(scheme == "issn", valid_issn(value))
        .when(scheme == "isbn", valid_isbn(value))
        .when(scheme == "orcid", valid_orcid(value))
        .when(scheme == "doi", valid_doi(value))
        .when(scheme == "pmid", valid_pmid(value))
        .otherwise(F.coalesce(value != "", F.lit(False)))
    )


def exists_check(ids: DataFrame, registry: DataFrame, key: str = "id", mode: str = "flag") -> DataFrame:
    """Whether an identifier is in the registry (column ``id``): 'flag' adds ``exists``, 'drop' keeps those that are."""
    known = registry.select(F.col("id").alias(key)).distinct()
    if mode == "drop":
        return ids.join(known, key, "left_semi")
    return ids.join(known.withColumn("exists", F.lit(True)), key, "left").withColumn("exists", F.coalesce("exists", F.lit(False)))
