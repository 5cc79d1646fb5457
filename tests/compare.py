"""Order-insensitive comparison of a Spark result with a DuckDB one."""

import decimal


def plain(v):
    if isinstance(v, float):
        return None if v != v else round(v, 5) + 0.0
    if isinstance(v, (list, tuple)):
        return tuple(plain(x) for x in v)
    if hasattr(v, "asDict"):
        return tuple(plain(x) for x in v)
    if isinstance(v, decimal.Decimal):
        return plain(float(v))
    return v.isoformat() if hasattr(v, "isoformat") else v


def same(df, relation):
    cols = sorted(df.columns)
    assert cols == sorted(relation.columns)
    ours = sorted((tuple(plain(r[c]) for c in cols) for r in df.collect()), key=repr)
    at = [relation.columns.index(c) for c in cols]
    theirs = sorted((tuple(plain(r[i]) for i in at) for r in relation.fetchall()), key=repr)
    assert ours == theirs
