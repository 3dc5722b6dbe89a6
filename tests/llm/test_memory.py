"""Memory of a Python worker that encodes, and of the batches on its way there."""

import json
import subprocess
import sys
from pathlib import Path

from tidegraph.llm.queries import MODEL

WORKER = """
import json, random, re, sys
from pathlib import Path
import pyarrow as pa
from tidegraph.llm import sentence_pieces
from tidegraph.llm.textpack import release

def held(name):
    return int(re.search(name + r":\\s+(\\d+)", Path("/proc/self/status").read_text())[1]) / 1024

rng = random.Random(7)
texts = [" ".join("".join(rng.choices("etaoinshrdlu", k=7)) for _ in range(100)) for _ in range(6000)]
batches = [pa.RecordBatch.from_arrays([pa.array(texts[a : a + 3000])], names=["_text"]) for a in (0, 3000)]
model = sentence_pieces._model(Path(sys.argv[1]).read_bytes())
release()
before, rows, right = held("VmRSS"), 0, 0
for out in sentence_pieces.encoded(iter(batches), model, 0, True):
    rows, right = rows + out.num_rows, right + sum(out.column(2).to_pylist())
del out
print(json.dumps([rows, right, held("VmHWM") - before, held("VmRSS") - before, len(model.known)]))
"""


def test_an_encoding_worker_stays_small():
    root = Path(__file__).resolve().parents[2]
    said = subprocess.run([sys.executable, "-c", WORKER, MODEL], cwd=root, capture_output=True, text=True, check=True).stdout
    rows, right, peak, left, known = json.loads(said)
    assert rows == right == 6000 and known > 500_000
    assert peak < 180 and left < 60, (peak, left)


def test_stages_send_small_batches(spark):
    import corpus_pipeline

    before, name = spark.conf.get(corpus_pipeline.BATCH_SETTING), corpus_pipeline.BATCH_SETTING
    docs = spark.createDataFrame([(1, "a b", None, None)], "doc_id long, text string, lang string, source string")
    try:
        for stage in (corpus_pipeline.STAGES[0][1], corpus_pipeline.STAGES[-1][1]):
            for given, want in (("64m", "4000000"), ("1m", "1m")):
                spark.conf.set(name, given)
                stage(spark, docs, "")
                assert spark.conf.get(name) == want
    finally:
        spark.conf.set(name, before)
