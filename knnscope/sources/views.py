"""Point views derived from the tables. The SQL text runs unchanged in Spark and DuckDB; see FIXTURES.md.

A name in braces is a table; Spark gets it as a DataFrame, DuckDB as the view of that name.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

from knnscope.io import table

_UNIT = "(({k}*7919+13)%10007)/10007e0 u, (({k}*104729+57)%99991)/99991e0 v"
_EVENTS = (
    "(select event_id id, event_type lab, ts, user_id, value, props, " + _UNIT.format(k="event_id") + " from {events}) t"
)


def _snap(expression: str) -> str:
    return f"floor(1000e0*({expression})+0.5e0)/1000e0"


def _by_label(x: dict[str, str], rest: str) -> str:
    return "case lab " + " ".join(f"when '{k}' then {v}" for k, v in x.items()) + f" else {rest} end"


def _shapes(x: dict, y: dict, keep: str) -> str:
    return (
        f"select id, lab, ts, user_id, value, props, {_snap(_by_label(x, '700*u'))} x, {_snap(_by_label(y, '500*v'))} y "
        f"from {_EVENTS} where {keep}"
    )


SHAPES = _shapes(
    {
        "click": "200+(100+16*(v-0.5e0))*cos(2*pi()*u)", "view": "40+620*u", "purchase": "430+200*u",
        "signup": "200+40*sqrt(v)*cos(2*pi()*u)",
    },
    {
        "click": "320+(100+16*(v-0.5e0))*sin(2*pi()*u)", "view": "90+50*sin(4*pi()*u)+24*(v-0.5e0)",
        "purchase": "220+200*u+30*(v-0.5e0)", "signup": "320+40*sqrt(v)*sin(2*pi()*u)",
    },
    "true",
)
SHAPES_B = _shapes(
    {
        "click": "180+(90+30*(v-0.5e0))*cos(pi()*u)", "view": "270+(90+30*(v-0.5e0))*cos(pi()+pi()*u)",
        "purchase": "450+30*v", "signup": "520+150*u",
    },
    {
        "click": "300+(90+30*(v-0.5e0))*sin(pi()*u)", "view": "270+(90+30*(v-0.5e0))*sin(pi()+pi()*u)",
        "purchase": "60+380*u", "signup": "380+60*v",
    },
    "id%5<>4",
)
SHAPES_C = _shapes(
    {
        "click": "120+30*sqrt(v)*cos(2*pi()*u)", "view": "350+90*sqrt(v)*cos(2*pi()*u)",
        "purchase": "560+60*sqrt(v)*cos(2*pi()*u)", "signup": "60+580*u",
    },
    {
        "click": "400+30*sqrt(v)*sin(2*pi()*u)", "view": "330+90*sqrt(v)*sin(2*pi()*u)",
        "purchase": "380+60*sqrt(v)*sin(2*pi()*u)", "signup": "100+40*(v-0.5e0)+60*sin(6*pi()*u)",
    },
    "id%5<>0",
)
LINE1D = (
    "select id, lab, "
    + _snap(_by_label({"click": "100+80*u", "view": "300+40*v", "purchase": "500+150*u", "signup": "820+30*v"}, "1000*u"))
    + f" x from {_EVENTS}"
)
LISTINGS = (
    "select id, price, nat, reg, pri, "
    + _snap("case when id%10=0 then 700*u else 60+140*reg+28*sqrt(v)*cos(2*pi()*u) end")
    + " x, "
    + _snap("case when id%10=0 then 360*v else 60+58*floor(nat/5)+28*sqrt(v)*sin(2*pi()*u) end")
    + " y from (select o_orderkey id, o_totalprice price, n_nationkey nat, n_regionkey reg, o_orderpriority pri, "
    + _UNIT.format(k="o_orderkey")
    + " from {orders} join {customer} on o_custkey=c_custkey join {nation} on c_nationkey=n_nationkey) t"
)
PHOTOS = (
    "select id, ts, user_id, props, "
    + _snap("case when id%16<12 then 100+((id%16)*173)%800+(12+(id%16)*2)*sqrt(v)*cos(2*pi()*u) else 1000*u end")
    + " x, "
    + _snap("case when id%16<12 then 100+((id%16)*389)%800+(12+(id%16)*2)*sqrt(v)*sin(2*pi()*u) else 1000*v end")
    + f" y from {_EVENTS}"
)
STATIONS = (
    "select id, rentals, "
    + _snap(
        "case when id%10<6 then 50+18*sqrt(v)*cos(2*pi()*u) "
        "when id%10<9 then 10+40*(id%10-6)+5*sqrt(v)*cos(2*pi()*u) else 100*u end"
    )
    + " x, "
    + _snap(
        "case when id%10<6 then 50+18*sqrt(v)*sin(2*pi()*u) "
        "when id%10<9 then case when id%10=7 then 95 else 10 end+5*sqrt(v)*sin(2*pi()*u) else 100*v end"
    )
    + " y from (select user_id id, count(*) rentals, "
    + _UNIT.format(k="user_id")
    + " from {events} group by user_id) t"
)
WEDGE = "select l_orderkey*8+l_linenumber id, l_quantity x, l_extendedprice/1000e0 y from {lineitem}"
VIEWS = {
    "shapes": SHAPES, "shapes_b": SHAPES_B, "shapes_c": SHAPES_C, "line1d": LINE1D, "listings": LISTINGS,
    "photos": PHOTOS, "stations": STATIONS, "wedge": WEDGE,
}
_NAME = re.compile(r"\{(\w+)\}")


def sql(spark: SparkSession, sf_dir: str, text: str) -> DataFrame:
    """Run SQL whose braces name tables of ``sf_dir``."""
    return spark.sql(text, **{n: table(spark, sf_dir, n) for n in set(_NAME.findall(text))})


def plain(text: str) -> str:
    """The same SQL for an engine that knows the tables by name."""
    return _NAME.sub(r"\1", text)


def view(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return sql(spark, sf_dir, VIEWS[name])
