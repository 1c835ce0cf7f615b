import pytest
from adaptivejoin.llm import common


class Conf(dict):
    def set(self, k, v):
        self[k] = v


class Session:
    def __init__(self, master, folder=None):
        self.conf = Conf({"spark.checkpoint.dir": folder} if folder else {})
        self.sparkContext = type("Context", (), {"master": master})()


def test_shared_folder_is_the_sessions_and_demanded_on_a_cluster():
    assert common.shared_folder(Session("spark://host:7077", "hdfs:///shared/")) == "hdfs:///shared"
    assert common.shared_folder(Session("local[4]")).startswith("file://")
    for master in ("spark://host:7077", "yarn", "local-cluster[3,2,1024]"):
        with pytest.raises(RuntimeError, match=r"spark\.checkpoint\.dir"):
            common.shared_folder(Session(master))


def test_a_worker_holds_one_object():
    made = []
    get = lambda name: common.held(name, lambda: made.append(name) or name.upper())
    assert [get("a"), get("a"), get("b"), get("a")] == ["A", "A", "B", "A"]
    assert made == ["a", "b", "a"] and len(common._held) == 1


def test_row_keys_are_stable_and_distinct(spark, tmp_path):
    rows = [(1, "x"), (1, "x"), (None, None), (None, None)]
    spark.createDataFrame(rows, "row_key long, row string").repartition(3).write.parquet(f"{tmp_path}/t")
    df = spark.read.parquet(f"{tmp_path}/t")
    work = common.Workspace(spark, "test")
    one, two = (sorted(r.row_key for r in common.row_keyed(df, work).collect()) for _ in range(2))
    assert one == two and len(set(one)) == 4
    shuffled = common.row_keyed(df.repartition(2), work)
    assert len({r.row_key for r in shuffled.collect()}) == 4 and shuffled.select("row.*").columns == ["row_key", "row"]
