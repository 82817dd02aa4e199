"""Ticket noise reduction: which tickets speak of the network, and who reports at all."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.columns import ratio

#: The action and the description keywords that suggest network trouble.
NETWORK_ACTIONS = ("Dispatch",)
NETWORK_KEYWORDS = ("data down", "noisy line", "slow speed")
MODES = ("both", "either", "action", "keyword")


def select_network_tickets(tickets: DataFrame, actions: Sequence[str] = NETWORK_ACTIONS, keywords: Sequence[str] = NETWORK_KEYWORDS, mode: str = "both") -> DataFrame:
    """tickets with is_network. One narrow pass; a null field never matches, and no keywords (none or null) match nothing."""
    if mode not in MODES:
        raise ValueError(f"mode is one of {MODES}")
    by_action = F.coalesce(F.col("action").isin(list(actions)), F.lit(False)) if mode != "keyword" else F.lit(False)
    words = F.lit(False)
    if mode != "action":
        for word in keywords or ():
            words = words | F.coalesce(F.contains(F.lower("description"), F.lit(word.lower())), F.lit(False))
    verdict = {"both": by_action & words, "either": by_action | words, "action": by_action, "keyword": words}[mode]
    return tickets.withColumn("is_network", verdict)


def action_shares(tickets: DataFrame) -> DataFrame:
    """(action, n, share): how tickets were resolved."""
    counted = tickets.groupBy("action").agg(F.count(F.lit(1)).alias("n"))
    total = counted.agg(F.sum("n").alias("total")).scalar()
    return counted.select("action", "n", ratio(F.col("n"), total).alias("share"))


def reporting_share(affected: DataFrame, tickets: DataFrame) -> DataFrame:
    """(affected, reporting, share): of the accounts in `affected`, those with a ticket."""
    accounts = affected.select("account").distinct()
    told = accounts.join(tickets.select("account").distinct().withColumn("told", F.lit(1)), "account", "left")
    return told.agg(F.count(F.lit(1)).alias("affected"), F.count("told").alias("reporting")).withColumn("share", ratio(F.col("reporting"), F.col("affected")))


def split_ticket_class(tickets: DataFrame) -> DataFrame:
    """tickets with ticket_class: maintenance if part of a primary issue, service if otherwise network-related."""
    kind = F.when(F.col("primary_id").isNotNull(), "maintenance").when(F.col("is_network"), "service").otherwise("other")
    return tickets.withColumn("ticket_class", kind)


def primary_groups(tickets: DataFrame) -> DataFrame:
    """One row per primary issue: n, accounts, first_created, last_closed."""
    named = tickets.where("primary_id is not null")
    return named.groupBy("primary_id").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("account").alias("accounts"), F.min("created").alias("first_created"), F.max("closed").alias("last_closed"))


def weigh_by_hour(tickets: DataFrame, by_day: tuple[int, int] = (8, 20), odd: float = 1.0) -> DataFrame:
    """tickets with weight: 1, and `odd` more each for a weekend and for the hours outside by_day, when few customers report.
    Rates take the weight's sum in place of the number of tickets."""
    hour, day = F.hour("created"), F.dayofweek("created")
    extra = F.when(day.isin(1, 7), F.lit(odd)).otherwise(0.0) + F.when((hour < by_day[0]) | (hour >= by_day[1]), F.lit(odd)).otherwise(0.0)
    return tickets.withColumn("weight", F.lit(1.0) + extra)
