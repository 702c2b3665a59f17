"""Pieces that several operators use.  Nulls in a text count as empty unless an operator says otherwise."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from walkengine.session import read_table, shared_dir, shuffle_partitions, staged  # noqa: F401  used by operators

#: The six white-space characters of ASCII that end a word.
BLANKS = " \t\n\x0b\x0c\r"
BLANK_RUN = r"[\x20\x09-\x0D]+"


def let(value: Column, body) -> Column:
    """``body`` of a value that is computed once for a row, also where ``body`` uses it inside a lambda."""
    return F.element_at(F.transform(F.array(value), body), 1)


def whole_text(text: str | Column = "text") -> Column:
    return F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))


def words_of(text: Column, gap: str = BLANK_RUN) -> Column:
    """The words between gaps, in order; none for an empty text."""
    return F.filter(F.split(text, gap), lambda w: w != "")


def only(docs: DataFrame, *names: str) -> DataFrame:
    """The named columns alone, so that further columns of a table never clash with derived ones."""
    return docs.select(*(F.col(f"`{n}`") for n in names))


def free_name(docs: DataFrame, name: str) -> str:
    """A name that no column of ``docs`` has, upper and lower case alike."""
    taken = {c.lower() for c in docs.columns}
    while name.lower() in taken:
        name += "_"
    return name


def spread_join(left: DataFrame, right: DataFrame, key: str | list[str], weight: str, how: str = "left") -> DataFrame:
    """``left`` joined on ``key`` (one column or several) with ``right``, a staged table of one row a key whose ``weight`` is at least the number of
    rows that ``left`` has with the key.

    A key with more than an even task's share of the weight has its row of ``right`` repeated, and its rows of ``left``
    dealt over as many tasks as its weight fills.  There are fewer such keys than tasks and at most twice as many repeated
    rows, however large the tables, which bounds what is broadcast.  A null key joins nothing, as in any join."""
    tasks = shuffle_partitions(left.sparkSession)
    keys = [key] if isinstance(key, str) else key
    total = right.agg(F.sum(weight)).first()[0] or 1
    share = F.greatest(F.lit(1), F.ceil(F.col(weight) * tasks / total)).cast("int")
    hot = right.withColumn("_deals", share).where("_deals > 1").select(*keys, "_deals")
    dealt = right.withColumn("_deal", F.explode(F.sequence(F.lit(0), share - 1)))
    rows = left.join(F.broadcast(hot), keys, "left")
    rows = rows.withColumn("_deal", F.when(F.col("_deals").isNull(), 0).otherwise(F.pmod(F.xxhash64(*left.columns), "_deals"))).drop("_deals")
    return rows.join(dealt, [*keys, "_deal"], how).drop("_deal")
