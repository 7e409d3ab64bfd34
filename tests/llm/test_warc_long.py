import glob

import pytest

from tilebalance.llm import warc
from tilebalance.llm.common import fresh_path


def test_a_url_above_a_mebibyte(spark):
    rows = [(1, "http://a/", "one"), (2, "http://b/" + "x" * (1 << 20), "two"), (3, "u", "three"), (4, "http://c/" + "y" * (3 << 20), None), (5, None, "five")]
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string").coalesce(1)
    path = fresh_path(spark, "long")
    warc.write(df, path)
    got = {r.record_id: r for r in warc.read(spark, path).collect()}
    assert {f"<urn:page:{i}>": (u, len(h or "")) for i, u, h in rows} == {k: (r.uri, r.payload_bytes) for k, r in got.items()}


@pytest.mark.parametrize("old,new", [(b"Content-Length: 6\r\n", b"Content-Length: 5\r\n"), (b"Content-Length: 6\r\n", b"Content-Length: x\r\n"), (b"WARC/1.1\r\n", b"WARC/1.0\r\n")])
def test_a_chain_that_ends_early_raises(spark, tmp_path, old, new):
    path = fresh_path(spark, "broken")
    warc.write(spark.createDataFrame([(i, "u", f"page {i}") for i in range(5)], "page_id bigint, url string, html string").coalesce(1), path, compression="none")
    data = open(glob.glob(path.removeprefix("file://") + "/part-*")[0], "rb").read()
    (tmp_path / "x.warc").write_bytes(data.replace(old, new, 1))
    with pytest.raises(Exception, match="the chain of records ends at byte"):
        warc.read(spark, str(tmp_path)).collect()
