"""Queries on the operators around the analyses, on inputs that the tables lack."""

import duckdb
import pyarrow as pa
import pyarrow.parquet as pq

from corpus_audit.plans.registry import ORACLES, QUERIES


def test_string_funcs_on_letters_of_several_bytes(spark, tmp_path):
    """Every code point of the planes with letters as a word, the words of the tables that differed, and odd spaces, against the SQL."""
    letters = [chr(i) for i in range(1, 0x1F000) if not 0xD800 <= i <= 0xDFFF]
    texts = ["Enrévi treen", "Ung ößau beerver", "Le éleéle", "\u3000a\u00a0 b", " ", "", None, *(f"{c} a{c}e x" for c in letters)]
    pq.write_table(pa.table({"doc_id": range(len(texts)), "text": pa.array(texts, pa.string()), "lang": ["en"] * len(texts)}), f"{tmp_path}/documents.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet'")
    want, got = con.sql(ORACLES["string_funcs"]).to_arrow_table(), QUERIES["string_funcs"](spark, str(tmp_path)).toArrow()
    con.register("want", want)
    con.register("got", got.select(want.column_names))
    assert got.num_rows == want.num_rows == len(texts)
    assert con.sql("(FROM want EXCEPT FROM got) UNION ALL (FROM got EXCEPT FROM want)").fetchall() == []
