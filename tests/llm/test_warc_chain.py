"""Archives whose headers are long, and ones whose records stop early."""

import pytest

from peakgroups.functions.storage import shared_path
from peakgroups.llm import warc


def test_long_url_does_not_break_the_chain(spark):
    # The url ends like the magic, and a payload quotes it without an end of a header.
    rows = [(1, "http://a/", "x"), (2, "http://b/" + "u" * 200_000 + "WARC/1.1", "y"), (3, "http://c/", "WARC/1.1\r\n" * 500), (4, None, "z")]
    path = shared_path(spark, "long")
    warc.write_archives(warc.deduplicated(spark.createDataFrame(rows, "page_id long, url string, html string").coalesce(1)), path)
    got = warc.read_archives(spark, path, block=1 << 14, payloads=True, whole=True).collect()
    assert {r.page_id: (r.url, bytes(r.payload).decode()) for r in got} == {i: (u, h) for i, u, h in rows}


def test_cut_archive_is_an_error_if_it_has_to_be_whole(spark, tmp_path):
    record = "WARC/1.1\r\nWARC-Type: response\r\nWARC-Record-ID: <urn:page:7>\r\nContent-Length: 5\r\n\r\nhello\r\n\r\n"
    (tmp_path / "part-0").write_bytes((record + record[:-9]).encode())
    assert [r.page_id for r in warc.read_archives(spark, str(tmp_path)).collect()] == [7]
    with pytest.raises(ValueError, match="stop at byte"):
        warc.read_archives(spark, str(tmp_path), whole=True)
