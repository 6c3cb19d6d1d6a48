"""What a task leaves allocated in its Python worker, which lives on beside the next stages."""

import os
import re
import subprocess
import sys

ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
RUN = """
import random, re
import pyarrow as pa
from shoal.llm import jaccard_join, sketch

def held():
    return sum(map(int, re.findall(r"Pss_(?:Anon|Shmem):\\s+(\\d+)", open("/proc/self/smaps_rollup").read()))) // 1024

def stage(df, columns, work, schema):
    from shoal.llm import storage
    work = getattr(storage, "tidy", lambda w: w)(work)
    rng = random.Random(1)
    words = ["".join(rng.choices("abcdefghij", k=6)) for _ in range(50_000)]
    batches = (pa.RecordBatch.from_arrays([pa.array([" ".join(rng.choices(words, k=250)) for _ in range(4000)])], ["text"]) for _ in range(8))
    before = held()
    for out in work(batches):
        pass
    del out
    raise SystemExit(print("left", held() - before))

sketch.arrow_stage, sketch.input_bytes = stage, lambda df: 510_000_000
sketch.repeated_items(None, [], jaccard_join._items(5), ranked=True)
"""


def test_sketch_gives_its_memory_back():
    done = subprocess.run([sys.executable, "-c", RUN], capture_output=True, text=True, timeout=120, cwd=ROOT, env={**os.environ, "PYTHONPATH": ROOT})
    left = re.search(r"left (-?\d+)", done.stdout)
    assert left, done.stderr[-2000:]
    assert int(left[1]) < 60


ENCODE = """
import random, resource
import public_tokenizers
import pyarrow as pa
from shoal.llm import pieces

def stage(df, columns, work, schema):
    rng = random.Random(1)
    words = lambda n: "".join(rng.choices("abcdefghij       ", k=n))  # nearly all distinct, as rare words are
    batches = [pa.RecordBatch.from_arrays([pa.array(range(2000)), pa.array([words(4000) for _ in range(2000)])], ["k", "t"])]
    pieces.table(path)
    peak = lambda: resource.getrusage(resource.RUSAGE_SELF).ru_maxrss // 1024
    before = peak()
    for out in work(iter(batches)):
        pass
    raise SystemExit(print("grown", peak() - before))

class Docs:
    schema = {"doc_id": type("F", (), {"dataType": type("T", (), {"simpleString": lambda self: "bigint"})()})()}

path = public_tokenizers.path("piece_bpe_32k.model")
pieces.arrow_stage, pieces.F = stage, type("F", (), {"col": str})
pieces.encoding_digests(Docs(), path)
"""


def test_encoding_works_in_little_memory():
    done = subprocess.run([sys.executable, "-c", ENCODE], capture_output=True, text=True, timeout=120, cwd=ROOT, env={**os.environ, "PYTHONPATH": ROOT})
    grown = re.search(r"grown (\d+)", done.stdout)
    assert grown, done.stderr[-2000:]
    assert int(grown[1]) < 180
