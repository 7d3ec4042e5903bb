import glob
import time

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from corpus_audit.llm import line_templates, piece_lattice
from corpus_audit.llm.common import tidied, written


def test_shuffle_files_of_finished_queries_go(spark):
    folders = list(spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirs())
    files = lambda: {f for d in folders for f in glob.glob(f"{d.getPath()}/*/shuffle_*.data")}
    before = files()
    rows = written(spark.range(100_000).groupBy((F.col("id") % 1000).alias("k")).agg(F.count(F.lit(1)).alias("n")), "tidied-test")
    tidied(spark, 0.0)
    for _ in range(100):
        if not files() - before:
            break
        time.sleep(0.1)
    assert not files() - before
    assert rows.count() == 1000


def test_open_lines_carry_no_places(spark, monkeypatch):
    stored, keep = {}, line_templates.written
    monkeypatch.setattr(line_templates, "written", lambda df, name, *codec: stored.setdefault(name, keep(df, name, *codec)))
    words = [f"w{c}" for c in "abcdefghijkl"]
    texts = [" ".join([*words[:5], x, *words[6:]]) for x in ("left", "right", "other")]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    assert {r["doc_id"] for r in line_templates.marked_lines(docs).collect()} == {1, 2}
    assert stored["template-open"].columns == ["line", "at", "bands"]
    assert stored["template-heads"].columns == ["band", "b"]


def test_dictionary_of_pieces_makes_no_row_objects():
    """A path is read from its buffers; characters without a piece are spelled by the lattice."""
    path = pa.array([[{"id": 5, "s": 0, "e": 1}, {"id": -1, "s": 1, "e": 2}], [], [{"id": 9, "s": 0, "e": 2}]], pa.list_(pa.struct([("id", pa.int32()), ("s", pa.int32()), ("e", pa.int32())])))
    coded = pa.table({"word": ["ab", "", "cd"], "path": path})

    class Spelled:
        def of(self, piece):
            return [100, 101] if piece == "b" else []

    got = piece_lattice._packed(coded, Spelled(), np.uint16)
    assert {w: np.frombuffer(x, np.uint16).tolist() for w, x in got.items()} == {"ab": [5, 100, 101], "": [], "cd": [9]}
