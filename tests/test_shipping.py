"""Kernels run where the package is not installed."""

import pickle
import subprocess
import sys

import pytest
from pyspark import cloudpickle

import textredun  # noqa: F401
from textredun.functions.signature import Setting, signature
from textredun.functions.sql import score_texts
from textredun.operators import metrics
from textredun.sources.shared import shared_folder

RUN = """
import pickle, sys
try:
    import textredun
    sys.exit("the package is here")
except ImportError:
    pass
print(pickle.load(open(sys.argv[1], "rb"))())
"""


@pytest.mark.parametrize("s", [Setting(n=3), Setting(metric="ttr", n=3), Setting(metric="zipf", n=3), Setting(metric="zipf", n=3, d="log", norm="difference"), Setting(unit="token", n=1)])
def test_scores_without_the_package(tmp_path, s):
    here, name = metrics.score_texts(["abcabcabc", "x"], [s])[1].tolist(), signature(s)
    for what, want in ((lambda: metrics.score_texts(["abcabcabc", "x"], [s])[1].tolist(), here), (lambda: score_texts(["abcabcabc"], name), [here[0][0]])):
        (tmp_path / "f").write_bytes(cloudpickle.dumps(what))
        out = subprocess.run([sys.executable, "-P", "-c", RUN, str(tmp_path / "f")], cwd=tmp_path, env={"PATH": ""}, capture_output=True, text=True)
        assert out.stdout.strip() == str(want), out.stderr
    assert pickle.loads(cloudpickle.dumps(metrics.power_model))


def test_no_machine_local_folder_on_a_cluster():
    class Conf(dict):
        pass

    class Session:
        def __init__(self, **conf):
            self.conf = Conf({"spark." + k.replace("_", "."): v for k, v in conf.items()})

    assert shared_folder(Session(checkpoint_dir="hdfs:///shared/")) == "hdfs:///shared"
    for master in ("yarn", "spark://host:7077", "local-cluster[3,2,3000]"):
        with pytest.raises(ValueError):
            shared_folder(Session(master=master))
    assert shared_folder(Session(master="local[2]")) == shared_folder(Session(master="local"))
