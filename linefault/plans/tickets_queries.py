"""Ticket noise reduction."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import tickets as TK
from ..sources import adapters as A
from . import oracle as O
from .base import tel
from .book import query, rounded


@query("a_network_tickets", f"WITH {O.BASE} SELECT ticket_id, action = 'Dispatch' AND regexp_matches(lower(description), 'data down|noisy line|slow speed') AS is_network FROM tkt")
def a_network_tickets(s, d):
    return TK.select_network_tickets(A.tickets(s, d)).select("ticket_id", "is_network")


@query("a_network_either", f"WITH {O.BASE} SELECT ticket_id, action = 'Dispatch' OR regexp_matches(lower(description), 'billing') AS is_network FROM tkt")
def a_network_either(s, d):
    return TK.select_network_tickets(A.tickets(s, d), keywords=("Billing",), mode="either").select("ticket_id", "is_network")


#: Words of the given tables' invented prose that stand in for the published keywords, which those texts never hold.
WORDS = ("network", "error", "line")
FREE_TEXT = " OR ".join(f"contains(lower(text), '{w}')" for w in WORDS)


@query("a_text_keywords", f"SELECT conv_id AS ticket_id, coalesce(bool_or({FREE_TEXT}), false) AS is_network FROM conversations WHERE role = 'user' GROUP BY conv_id")
def a_text_keywords(s, d):
    """Keyword selection on free text: a conversation's ticket is all of its user turns."""
    rows = A.text_tickets(s, d).withColumn("action", F.lit(None).cast("string"))
    return TK.select_network_tickets(rows, keywords=WORDS, mode="keyword").select("ticket_id", "is_network")


@query("a_document_keywords", f"SELECT doc_id AS ticket_id, coalesce({FREE_TEXT}, false) AS is_network FROM documents")
def a_document_keywords(s, d):
    """The same over whole documents, for volume: one narrow scan."""
    rows = A.document_tickets(s, d).withColumn("action", F.lit(None).cast("string"))
    return TK.select_network_tickets(rows, keywords=WORDS, mode="keyword").select("ticket_id", "is_network")


@query("a_action_shares", f"WITH {O.BASE} SELECT action, count(*) AS n, round(count(*) / (SELECT count(*) FROM tkt), 6) AS share FROM tkt GROUP BY action")
def a_action_shares(s, d):
    return TK.action_shares(A.tickets(s, d)).select("action", "n", *rounded("share"))


@query("a_reporting_share", f"""WITH {O.BASE}, hit AS (SELECT DISTINCT account FROM tel WHERE maint), told AS (SELECT DISTINCT account FROM tkt WHERE is_maintenance)
SELECT count(*) AS affected, count(t.account) AS reporting, round(count(t.account) / count(*), 6) AS share FROM hit LEFT JOIN told t USING (account)""")
def a_reporting_share(s, d):
    """Who reports a planted outage: a property of the data, so the plant itself is what is counted."""
    return TK.reporting_share(tel(s, d).where("maint"), A.tickets(s, d).where("is_maintenance")).select("affected", "reporting", *rounded("share"))


@query("a_primary_groups", f"WITH {O.BASE} SELECT primary_id, count(*) AS n, count(DISTINCT account) AS accounts, min(created) AS first_created, max(closed) AS last_closed FROM tkt WHERE primary_id IS NOT NULL GROUP BY primary_id")
def a_primary_groups(s, d):
    return TK.primary_groups(A.tickets(s, d))


@query("a_ticket_class", f"WITH {O.BASE} SELECT CASE WHEN primary_id IS NOT NULL THEN 'maintenance' WHEN is_network THEN 'service' ELSE 'other' END AS ticket_class, count(*) AS n FROM tkt GROUP BY 1")
def a_ticket_class(s, d):
    return TK.split_ticket_class(A.tickets(s, d)).groupBy("ticket_class").agg(F.count(F.lit(1)).alias("n"))


ODD = "1.0 + (extract('isodow' FROM created) >= 6)::INT + (extract('hour' FROM created) < 8 OR extract('hour' FROM created) >= 20)::INT"


@query("a_ticket_weights", f"WITH {O.BASE} SELECT ticket_id, {ODD} AS weight FROM tkt WHERE is_network")
def a_ticket_weights(s, d):
    """Extension: tickets at unusual times weigh more."""
    return TK.weigh_by_hour(A.tickets(s, d).where("is_network")).select("ticket_id", "weight")
