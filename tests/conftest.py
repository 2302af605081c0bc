import os
import random
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


@pytest.fixture(scope="session")
def spark(tmp_path_factory):
    from pyspark.sql import SparkSession

    folder = tmp_path_factory.mktemp("spark")
    session = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.driver.memory", "4g")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", f"file://{folder}/checkpoints")
        .config("spark.sql.warehouse.dir", f"{folder}/warehouse")
        .getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


DATA = "/root/testdata/sf0.001"


def random_edges(n, m, seed, distinct=True):
    """(u, v, w, channel) rows of a random signed graph; channel keeps parallel edges apart."""
    rnd = random.Random(seed)
    sizes = rnd.sample(range(1, 10 * m + 1), m) if distinct else [rnd.randint(1, 6) for _ in range(m)]
    rows = []
    for k in range(m):
        a, b = sorted(rnd.sample(range(n), 2))
        rows.append((a, b, float(rnd.choice([-1, 1]) * sizes[k]), k))
    return rows
