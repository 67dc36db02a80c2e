"""op5_licence_scan against its SQL on relatives, wrapped notices, blank lines and notices within prose."""

import duckdb

from rowgraph.llm import licences, oracle, queries

T = licences.TEMPLATES


def test_licence_scan_equals_its_sql(spark, tmp_path):
    wrapped = T["ISC"][0].replace(". ", ".\n")
    texts = [None, "", "\n", *(t for ts in T.values() for t in ts), wrapped, f"a\n \t\n{wrapped}\n\r\nb", f"a\n\n\n{wrapped}\n\n\nb", f"some prose before it {T['MIT'][1]} and after it " * 2, wrapped.replace("\n", "\n\n"), f"{T['GPL-3.0'][1]}\n{T['MIT'][0]}"]
    spark.createDataFrame(list(enumerate([*texts, *texts])), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = queries.QUERIES["op5_licence_scan"](spark, str(tmp_path)).select("doc_id", "licence", "dice", "licences").collect()
    con = duckdb.connect()
    con.sql(f"create view documents as select * from '{tmp_path}/documents.parquet/*.parquet'")
    want = con.sql(f"select doc_id, licence, dice, licences from ({oracle.ORACLE['op5_licence_scan']})").fetchall()
    near = lambda rows: sorted(((r[0], r[1], round(r[2], 9), r[3]) for r in rows), key=repr)
    assert near(got) == near(want)
    assert any("AGPL-3.0,GPL-2.0,GPL-3.0,LGPL-3.0" in r["licences"] for r in got)
