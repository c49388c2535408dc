"""Comparison of a DataFrame with its SQL twin, order left aside."""

import math


def plain(v):
    if v is None or (isinstance(v, float) and math.isnan(v)):
        return "null"
    if hasattr(v, "item"):
        v = v.item()
    if isinstance(v, float) and not isinstance(v, bool):
        return str(int(v)) if v == int(v) else repr(round(v, 6))
    return str(v)


def rows(df):
    names = sorted(df.columns)
    return names, sorted(tuple(plain(r[n]) for n in names) for r in df.collect())


def twin(duck, sql):
    e = duck.sql(sql)
    names = sorted(e.columns)
    return names, sorted(tuple(plain(v) for v in r) for r in e.select(*[f'"{n}"' for n in names]).fetchall())
