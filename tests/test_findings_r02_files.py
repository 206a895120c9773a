"""Case of the pipeline's finding of round 2: tables written on the way start no process in the driver."""

from urllib.parse import urlparse
from pathlib import Path

from bigtopics.sources.files import settle, temporary


def test_settled_tables_have_their_rows_and_no_mark_of_success(spark):
    with temporary(spark) as keep:
        tables = [settle(spark.range(50), "inside"), keep(spark.range(50), "outside")]
        for t in (*tables, settle(spark.range(50), "inside")):
            assert sorted(r.id for r in t.collect()) == list(range(50))
            folder = Path(urlparse(t.inputFiles()[0]).path).parent
            assert not list(folder.glob("*_SUCCESS*")) and list(folder.glob("part-*"))
