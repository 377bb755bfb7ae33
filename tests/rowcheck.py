"""Comparison of a frame with SQL."""


def canonical(value):
    import datetime
    import decimal

    if isinstance(value, float):
        return "nan" if value != value else repr(round(value, 6) + 0.0)
    if isinstance(value, decimal.Decimal):
        return str(value.normalize())
    if isinstance(value, (bytes, bytearray)):
        return bytes(value).hex()
    if isinstance(value, datetime.datetime):
        return value.replace(tzinfo=None).isoformat()
    return repr(value)


def same_rows(df, con, sql):
    """The rows of a frame against those of a SQL text, by column name and in any order."""
    cols = sorted(df.columns)
    ours = sorted(tuple(map(canonical, r)) for r in df.select(*cols).collect())
    rel = con.execute(sql)
    names = [c[0] for c in rel.description]
    assert sorted(names) == cols
    theirs = sorted(tuple(canonical(r[names.index(c)]) for c in cols) for r in rel.fetchall())
    assert ours == theirs
    return len(ours)
