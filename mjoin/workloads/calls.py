"""Call-record and journey queries: lead, mid, tail and peer are aliases of one table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..query import MultiJoinQuery, band, multi_join
from ..sources import calls, legs

CALLS_SQL = """WITH calls AS (SELECT event_id AS rid, user_id AS id, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE))::INT AS d,
(hour(ts) * 3600 + minute(ts) * 60 + second(ts))::BIGINT AS bt, value AS l, CAST(json_extract_string(props, '$.k') AS INT) AS bsc, event_type AS kind FROM events)"""
LEGS_SQL = "WITH legs AS (SELECT event_id AS rid, event_type AS leg, ts AS dep, ts + to_minutes(CAST(floor(value) AS INT)) AS arr FROM events)"


def relation(spark: SparkSession, sf_dir: str, condition: str | None = None) -> DataFrame:
    df = calls(spark, sf_dir)
    return df.where(condition) if condition else df


def w1(c: DataFrame) -> MultiJoinQuery:
    """Earlier and longer calls, and calls of one station and day."""
    return multi_join(lead=c, mid=c, tail=c).on("lead.bt <= mid.bt", "lead.l >= mid.l", "mid.bsc = tail.bsc", "mid.d = tail.d").select(id="lead.id").build()


def w2(c: DataFrame) -> MultiJoinQuery:
    """As w1 with other stations."""
    return multi_join(lead=c, mid=c, tail=c).on("lead.bt <= mid.bt", "lead.l >= mid.l", "mid.bsc <> tail.bsc", "mid.d = tail.d").select(id="lead.id").build()


def concurrent(c: DataFrame, station: str, first: str | None = None) -> MultiJoinQuery:
    """Pairs of calls of a day that overlap in time, at the same (=) or other (<>) stations."""
    q = multi_join(lead=c, mid=c).on("lead.d = mid.d", f"lead.bsc {station} mid.bsc", "lead.rid <> mid.rid", "lead.bt <= mid.bt", "lead.bt + 60 * lead.l >= mid.bt").select(lead_rid="lead.rid", mid_rid="mid.rid")
    return (q.where("lead", first) if first else q).build()


def three_days(c: DataFrame, station: str, same_id: bool) -> MultiJoinQuery:
    """Calls on three days in a row, and a further one at the same or another station as the first."""
    on = ["lead.d < mid.d", "mid.d < tail.d", "lead.d + 3 > tail.d", f"lead.bsc {station} peer.bsc"]
    if same_id:
        on += ["lead.id = mid.id", "mid.id = tail.id", "lead.id = peer.id"]
    return multi_join(lead=c, mid=c, tail=c, peer=c).on(*on).select(id="lead.id").build()


def itinerary(spark: SparkSession, sf_dir: str) -> MultiJoinQuery:
    """Journeys signup, view, purchase with stays of more than 5 and less than 60 minutes."""
    leg = legs(spark, sf_dir)
    of = lambda kind: leg.where(F.col("leg") == kind)
    low, high = "interval 5 minutes", "interval 60 minutes"
    return multi_join(a=of("signup"), b=of("view"), c=of("purchase")).on(*band(1, "a.arr", "b.dep", low, high), *band(3, "b.arr", "c.dep", low, high)).select(a_rid="a.rid", b_rid="b.rid", c_rid="c.rid").build()


W1_WHERE = "lead.bt <= mid.bt AND lead.l >= mid.l AND mid.bsc = tail.bsc AND mid.d = tail.d"
W2_WHERE = W1_WHERE.replace("mid.bsc =", "mid.bsc <>")
W3_WHERE = "lead.d < mid.d AND mid.d < tail.d AND lead.d + 3 > tail.d AND lead.bsc = peer.bsc"
W4_WHERE = W3_WHERE.replace("lead.bsc =", "lead.bsc <>")
SAME_ID = " AND lead.id = mid.id AND mid.id = tail.id AND lead.id = peer.id"


def counts_sql(aliases: str, where: str, condition: str = "true") -> str:
    tables = ", ".join(f"(SELECT * FROM calls WHERE {condition}) {a}" for a in aliases.split())
    return f"{CALLS_SQL} SELECT lead.id AS id, count(*)::BIGINT AS n FROM {tables} WHERE {where} GROUP BY lead.id"


#: The printed forms counted without visiting each combination: equal rows first, then leaf by leaf, as grouped_counts does.
GROUPED_SQL = {
    "w1": f"""{CALLS_SQL}, tail AS (SELECT bsc, d, count(*) AS w FROM calls GROUP BY ALL),
mid AS (SELECT bt, l, sum(w) AS w FROM calls JOIN tail USING (bsc, d) GROUP BY ALL)
SELECT lead.id AS id, sum(mid.w)::BIGINT AS n FROM calls lead JOIN mid ON lead.bt <= mid.bt AND lead.l >= mid.l GROUP BY lead.id""",
    "w2": f"""{CALLS_SQL}, tail AS (SELECT bsc, d, count(*) AS w FROM calls GROUP BY ALL),
mid AS (SELECT bt, l, sum(w) AS w FROM calls c JOIN tail t ON c.bsc <> t.bsc AND c.d = t.d GROUP BY ALL)
SELECT lead.id AS id, sum(mid.w)::BIGINT AS n FROM calls lead JOIN mid ON lead.bt <= mid.bt AND lead.l >= mid.l GROUP BY lead.id""",
} | {
    name: f"""{CALLS_SQL}, days AS (SELECT d, count(*) AS w FROM calls GROUP BY d), lead AS (SELECT id, d, bsc, count(*) AS w FROM calls GROUP BY ALL), peer AS (SELECT bsc, count(*) AS w FROM calls GROUP BY bsc)
SELECT lead.id AS id, sum(lead.w * mid.w * tail.w * peer.w)::BIGINT AS n FROM lead, days mid, days tail, peer
WHERE lead.d < mid.d AND mid.d < tail.d AND lead.d + 3 > tail.d AND lead.bsc {op} peer.bsc GROUP BY lead.id"""
    for name, op in (("w3", "="), ("w4", "<>"))
}


def concurrent_sql(station: str, first: str = "true") -> str:
    return f"""{CALLS_SQL} SELECT lead.rid AS lead_rid, mid.rid AS mid_rid FROM calls lead, calls mid WHERE {first} AND lead.d = mid.d AND lead.bsc {station} mid.bsc
AND lead.rid <> mid.rid AND lead.bt <= mid.bt AND lead.bt + 60 * lead.l >= mid.bt"""


ITINERARY_SQL = f"""{LEGS_SQL} SELECT a.rid AS a_rid, b.rid AS b_rid, c.rid AS c_rid FROM legs a, legs b, legs c WHERE a.leg = 'signup' AND b.leg = 'view' AND c.leg = 'purchase'
AND a.arr + INTERVAL 5 MINUTE < b.dep AND b.dep < a.arr + INTERVAL 60 MINUTE AND b.arr + INTERVAL 5 MINUTE < c.dep AND c.dep < b.arr + INTERVAL 60 MINUTE"""
