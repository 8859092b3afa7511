def rows(df):
    """Rows as sorted text, for DataFrames of either engine."""
    p = df.toPandas() if hasattr(df, "toPandas") else df
    cols = sorted(p.columns)
    return cols, sorted(str(tuple(None if x is None or x != x else x for x in r)) for r in p[cols].astype(object).itertuples(index=False, name=None))
