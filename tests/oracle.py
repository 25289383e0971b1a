"""Compares a query with its SQL: same columns, same rows in any order."""

import datetime
import decimal
import math


def plain(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else repr(v)
    if isinstance(v, decimal.Decimal):
        return f"decimal {v}"
    if isinstance(v, datetime.datetime):
        return v.isoformat()
    return repr(v)


def compare(df, con, sql):
    rows = con.execute(sql)
    names = [c[0] for c in rows.description]
    assert sorted(df.columns) == sorted(names)
    order = sorted(names)
    mine = sorted(tuple(plain(r[c]) for c in order) for r in df.collect())
    theirs = sorted(tuple(plain(r[names.index(c)]) for c in order) for r in rows.fetchall())
    assert mine == theirs
