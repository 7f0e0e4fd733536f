"""Rows of both engines in one comparable form."""

import datetime
import decimal


def plain(v):
    if isinstance(v, decimal.Decimal):
        return float(v)
    if isinstance(v, float):
        return round(v, 9) + 0.0
    if isinstance(v, datetime.datetime):
        return v.replace(tzinfo=None)
    return v


def spark_rows(df):
    columns = sorted(df.columns)
    return columns, sorted((tuple(plain(v) for v in r) for r in df.select(*columns).collect()), key=repr)


def duck_rows(con, sql):
    r = con.execute(sql)
    names = [c[0] for c in r.description]
    columns = sorted(names)
    at = [names.index(c) for c in columns]
    return columns, sorted((tuple(plain(x[i]) for i in at) for x in r.fetchall()), key=repr)
