"""The same queries in the padded tier: filters clear validity, groups and joins keep rows, sizes stay public.

Joins are stacked passes wherever left keys are unique (or the join is a semi or anti join); inner ones are
trimmed back where the public rule says so. A join of two sides with repeated keys has no public size
below their product and is a native one.
"""

from __future__ import annotations

from . import prior, tpch
from .tables import padded_table

QUERIES = {}
SQL = {}


def _padded(fn):
    return lambda spark, sf_dir: fn(lambda name: padded_table(spark, sf_dir, name)).reveal()


for _m in (tpch, prior):
    for _name, _fn in _m.FUNCTIONS.items():
        if _name.startswith(("tpch_q", "prior_", "owner_")):
            QUERIES[f"{_name}_padded"] = _padded(_fn)
            SQL[f"{_name}_padded"] = _m.SQL[_name]
