"""What a merge keeps: stored values first, then first occurrences; order of contributors; containment."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from biblake.functions.text import name_key


def merge_fields(rows: DataFrame, by: str, rank: list[str], fields: list[str], ids: str | None = None) -> DataFrame:
    """One row a group: each field's first value by rank that is neither null nor empty; identifiers are united.

    The rank starts with 0 for stored rows, so a stored value is never changed and only gaps are filled.
    """
    place = F.struct(*rank)
    some = lambda c: F.when(F.col(c).isNotNull() & (F.col(c).cast("string") != ""), place)
    picks = [F.min_by(c, some(c)).alias(c) for c in fields]
    united = [F.array_sort(F.array_distinct(F.flatten(F.collect_set(ids)))).alias(ids)] if ids else []
    return rows.groupBy(by).agg(*picks, *united)


def merge_contributors(stored: DataFrame, new: DataFrame) -> DataFrame:
    """(br, role, agent, pos): the stored order stays, unseen agents follow in the order they appear.

    stored: (br, role, agent, pos). new: (br, role, agent, at), at any orderable column, such as a struct of file, row and place.
    """
    kept = stored.groupBy("br", "role", "agent").agg(F.min("pos").alias("_pos"))
    seen = new.groupBy("br", "role", "agent").agg(F.min("at").alias("_at"))
    both = kept.join(seen, ["br", "role", "agent"], "full_outer")
    order = Window.partitionBy("br", "role").orderBy(F.col("_pos").isNull(), "_pos", "_at", "agent")
    return both.select("br", "role", "agent", F.row_number().over(order).alias("pos"))


def chain(roles: DataFrame, eid: str = "agent") -> DataFrame:
    """Adds next: the role that follows in the list of its (br, role)."""
    return roles.withColumn("next", F.lead(eid).over(Window.partitionBy("br", "role").orderBy("pos")))


def match_people_by_name(people: DataFrame) -> DataFrame:
    """(br, name_key, agent, n): people of one publication without an identifier are one if given and family name agree, in any role.

    people: (br, pos, given, family, agent); agent is null without an identifier. A namesake with an identifier is taken, the first in the list.
    """
    rows = people.withColumn("name_key", name_key(F.col("given"), F.col("family")))
    return rows.groupBy("br", "name_key").agg(F.min_by("agent", F.when(F.col("agent").isNotNull(), F.struct("pos", "agent"))).alias("agent"), F.count("*").alias("n"))


def merge_containment(rows: DataFrame, merges: DataFrame | None = None) -> DataFrame:
    """(venue, volume, issue, n, part_of): volumes of one venue are one if their value is, issues if value and volume are.

    rows: (br, venue, volume, issue). merges: (loser, survivor) of venues; children of a loser are keyed anew under the survivor.
    part_of names the parent: the volume if there is one, else the venue.
    """
    if merges is not None:
        rows = rows.join(merges.select(F.col("loser").alias("venue"), "survivor"), "venue", "left").withColumn("venue", F.coalesce("survivor", "venue"))
    return rows.groupBy("venue", "volume", "issue").agg(F.count("*").alias("n")).withColumn("part_of", F.concat_ws("/", F.col("venue").cast("string"), F.col("volume").cast("string")))


def dedup_roles(roles: DataFrame) -> DataFrame:
    """One role for each (br, role, agent), at its first place."""
    return roles.groupBy("br", "role", "agent").agg(F.min("pos").alias("pos"))


def dedup_pages(pages: DataFrame) -> DataFrame:
    return pages.dropDuplicates(["br", "first_page", "last_page"])


def venue_key(has_id: Column, eid: Column, title: Column) -> Column:
    """What venues are counted by: the entity if it has an external identifier, else its title. Not used to merge."""
    return F.when(has_id, eid).otherwise(F.lower(F.trim(title)))
