"""Ordinary long pages are cut into segments without any options."""

from qacurate.llm import warc
from qacurate.staging import fresh_path


def test_long_pages_have_segments_by_default(spark):
    rows = [(1, "u", "short"), (2, "v", "".join(chr(97 + k * k % 23) for k in range(40_000)))]
    path = fresh_path(spark, "warc-default")
    warc.write_warc(spark.createDataFrame(rows, "page_id long, url string, html string"), path)
    got = {r.page_id: r for r in warc.read_warc(spark, path).collect()}
    assert got[2].segments > 1 and got[1].segments == 1
    assert all(got[i].problem is None and bytes(got[i].payload).decode() == t for i, _, t in rows)
