import os

import pytest
from llm_texts import prose
from pyspark.sql import SparkSession


@pytest.fixture(scope="session")
def spark():
    session = (
        SparkSession.builder.master("local[4]").appName("tests")
        .config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "4g")
        .config("spark.sql.warehouse.dir", f"/tmp/clipflow-warehouse-{os.getpid()}")
        .getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    return session


@pytest.fixture(scope="session")
def corpus():
    """Rows (doc_id, text) with copies, near copies, shared passages, ties, nulls, odd characters and a very long text."""
    passage, long_one = prose(1, 60), prose(2, 30_000)
    rows = [(i, prose(100 + i, 20 + 7 * i)) for i in range(1, 25)]
    rows += [(30, rows[3][1]), (31, rows[3][1].replace(" ", "\n\t ")), (29, rows[3][1])]
    rows += [(32, prose(5, 40) + " " + passage + " " + prose(6, 12)), (33, passage), (34, "\n" + passage + " tail"), (35, prose(7, 9) + " " + passage)]
    rows += [(36, long_one), (37, long_one[5_000:] + " end"), (38, None), (39, ""), (40, "   \n"), (41, "one"), (42, "Ünïcödé ß É 中文 😀 " * 9), (43, "Ünïcödé ß É 中文 😀 " * 9)]
    rows += [(44, "aaaa" * 60), (45, "aaaa" * 50), (46, "ab " * 40), (47, " ".join(rows[8][1].split()[:70] + ["changed"] + rows[8][1].split()[71:]))]
    rows += [(48, None), (49, "one")]
    return rows
