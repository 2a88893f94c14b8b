"""Comparison of a query's rows with its SQL, and a plain model of sets under updates."""

SMALL = "/root/testdata/sf0.001"


def plain(v):
    if isinstance(v, float):
        return float(f"{v:.9g}")
    if isinstance(v, (list, tuple)):
        return tuple(plain(x) for x in v)
    return v


def same_rows(df, con, sql):
    result = con.execute(sql)
    names = [c[0] for c in result.description]
    order = sorted(df.columns)
    assert sorted(names) == order
    ours = sorted((tuple(plain(r[c]) for c in order) for r in df.collect()), key=repr)
    theirs = sorted((tuple(plain(r[names.index(c)]) for c in order) for r in result.fetchall()), key=repr)
    assert ours == theirs


def walk(updates):
    """Members of every set after (seq, set_id, element, op) updates."""
    sets = {}
    for _, s, x, op in sorted(updates):
        (sets.setdefault(s, set()).add if op > 0 else sets.setdefault(s, set()).discard)(x)
    return sets
