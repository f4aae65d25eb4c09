import duckdb
import pyarrow as pa


def duck(sql, **tables):
    con = duckdb.connect()
    for name, (rows, schema) in tables.items():
        cols = {f.name: [r[i] for r in rows] for i, f in enumerate(schema)}
        con.register(name, pa.table(cols, schema=schema))
    return sorted(map(tuple, con.execute(sql).fetchall()), key=str)


DOCS = pa.schema([("doc_id", pa.int64()), ("text", pa.string()), ("lang", pa.string()), ("source", pa.string()), ("n_chars", pa.int64())])
ITEMS = pa.schema([("item_id", pa.int64()), ("text", pa.string())])
DOC_DDL = "doc_id long, text string, lang string, source string, n_chars long"


def docs(pairs):
    return [(d, t, "en", "s", len(t or "")) for d, t in pairs]


def rows(df, cols):
    return sorted((tuple(r[c] for c in cols) for r in df.collect()), key=str)
