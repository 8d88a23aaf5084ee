import os

import pytest

from rowsketch import shared


def test_discard_and_scratch(spark):
    a = shared.materialise(spark.range(5), "a")
    path = a._rowsketch_path.replace("file://", "")
    assert os.path.isdir(path) and a.count() == 5
    assert os.path.dirname(path).endswith(spark.sparkContext.applicationId)
    shared.discard(a)
    assert not os.path.exists(path)
    shared.discard(spark.range(3))
    shared.discard(None)


def test_a_cluster_needs_a_shared_folder():
    from unittest.mock import MagicMock

    session = MagicMock()
    session.conf.get.side_effect = lambda name, default=None: default
    session.sparkContext._jsc.sc().getCheckpointDir().isDefined.return_value = False
    session.sparkContext.master = "spark://host:7077"
    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        shared.shared_dir(session)
    session.sparkContext.master = "local[4]"
    assert shared.shared_dir(session).startswith("file:///")
