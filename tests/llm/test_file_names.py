"""Flat files and archives of any name are read, hidden and marker files are not."""

from corrutil.llm import tokencount, warc


def test_files_of_any_name_are_read(spark, tmp_path):
    docs = spark.createDataFrame([(i, f"text number {i}") for i in range(4)], "doc_id bigint, text string")
    flat = tokencount.write_flat(docs, f"file://{tmp_path}/flat")
    packed = warc.write_archives(docs.selectExpr("doc_id AS page_id", "'http://a.b/' || doc_id AS url", "text AS html"), f"file://{tmp_path}/warc")
    for at in ("flat", "warc"):
        for n, f in enumerate(sorted((tmp_path / at).glob("part-*"))):
            f.rename(tmp_path / at / f"shard{n}.bin")
    assert sorted(r["label"] for r in tokencount.count_flat(spark, flat).collect()) == [0, 1, 2, 3]
    assert {r["page_id"] for r in warc.read_archives(spark, packed, payload=False).where("page_id IS NOT NULL").collect()} == {0, 1, 2, 3}
