"""Delimited text, JSON, ORC and rows as sources; the method called on a view."""

import numpy as np
import pytest

from devfed.functions import sqlfns
from devfed.operators import rounds
from devfed.operators.rounds import FedConfig
from devfed.sources import checkpoints, tables

SCHEMA = "id long, client_id int, x1 double, label double"
ROWS = [(k, k % 3, float(np.sin(k)), float(k % 2)) for k in range(60)]


def test_sources_give_the_same_rows(spark, tmp_path):
    df = tables.rows(spark, ROWS, SCHEMA)
    df.write.csv(str(tmp_path / "c"), sep=";", header=True)
    df.write.json(str(tmp_path / "j"))
    df.write.orc(str(tmp_path / "o"))
    read = {"c": tables.csv(spark, str(tmp_path / "c"), SCHEMA), "j": tables.json(spark, str(tmp_path / "j"), SCHEMA), "o": tables.orc(spark, str(tmp_path / "o"))}
    for name, found in read.items():
        assert sorted(map(tuple, found.select("id", "client_id", "x1", "label").collect())) == ROWS, name


def test_malformed_rows_fail_the_read(spark, tmp_path):
    (tmp_path / "bad.csv").write_text("id;client_id;x1;label\n1;2;3.5;1.0\n1;two;3.5;1.0\n")
    with pytest.raises(Exception, match="(?i)malformed|FAILFAST|CAST_INVALID"):
        tables.csv(spark, str(tmp_path / "bad.csv"), SCHEMA).collect()


def test_training_by_a_views_name(spark):
    df = tables.rows(spark, ROWS, SCHEMA)
    df.createOrReplaceTempView("owned_rows")
    found = sqlfns.federated_train("owned_rows", ["x1"], ["id"], {"rounds": 3, "epochs": 2}, spark=spark, min_rows=5, cap=2).orderBy("round").collect()
    want = rounds.fit(df, ["x1"], ["id"], FedConfig(rounds=3, epochs=2), min_rows=5, cap=2)
    assert np.allclose([r["w"] for r in found], want.vectors) and [r["method"] for r in found] == ["federated"] * 3


def test_checkpoints_need_a_shared_folder_on_a_cluster():
    class Context:
        master = "spark://host:7077"

        def getConf(self):
            return {}

        def getCheckpointDir(self):
            return None

    class Session:
        sparkContext = Context()

    with pytest.raises(ValueError):
        checkpoints.folder(Session())
