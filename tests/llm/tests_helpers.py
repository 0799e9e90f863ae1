def plain(v):
    return f"{v:.9g}" if isinstance(v, float) else str(v)


def compare(df, rel):
    columns = sorted(df.columns)
    assert sorted(rel.columns) == columns
    at = [rel.columns.index(c) for c in columns]
    got = sorted(tuple(map(plain, r)) for r in df.select(*columns).collect())
    assert got == sorted(tuple(plain(r[i]) for i in at) for r in rel.fetchall())
