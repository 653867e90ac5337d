"""One very long text: every operator that reads whole texts in Python stays within a worker's memory."""

import subprocess
import sys
from pathlib import Path

import pytest

ROOT = str(Path(__file__).resolve().parents[2])
MOST_MB = 1000

BEGIN = f"""
import sys, resource
sys.path.insert(0, {ROOT!r})
import numpy as np, pyarrow as pa
r = np.random.default_rng(1)
words = np.array(["".join(map(chr, 97 + r.integers(0, 26, r.integers(2, 10)))) for _ in range(50_000)])
def text(mb):
    return " ".join(" ".join(words[r.integers(0, len(words), 150_000)]) for _ in range(mb))[: mb << 20]
def batch(t):
    return pa.RecordBatch.from_arrays([pa.array([1]), pa.array([t])], ["doc_id", "text"])
"""
RUNS = {
    "op2": """
from winsub.llm import op02_sentencepiece as op
import public_tokenizers as P
p = op.Pieces(P.path("piece_bpe_32k.model"))
for t in (text(24), text(3).replace(" ", "")):  # words, and one unbroken run
    ids = p.encode(t)
    assert p.decode(ids) == t
""",
    "op3": """
from winsub.llm import op03_language_id as op
from winsub.llm.common import utf8
m = op.Model(["a", "b", "c", "d"], r.integers(0, 50, (4, op.BUCKETS)))
t = text(24)
whole = m.predict(*utf8(pa.array([t])))
op.WORDS = 1 << 12
part = m.predict(*utf8(pa.array([t])))
assert whole[0] == part[0] and abs(whole[1][0] - part[1][0]) < 1e-6
""",
    "op6": """
from winsub.llm import op06_parity_join as op
n = sum(b.num_rows for b in op._profile(iter([batch(text(24))])))
n += sum(b.num_rows for b in op._emit(np.empty(0, np.uint64)).args[0](iter([batch(text(24))])))
assert n > 1000
""",
    "op7": """
from winsub.llm import op07_quality as op
from winsub.llm.common import utf8
m = op.Attention()
m.fitted = True
t = text(24)
whole = m.score(*utf8(pa.array([t])))
op.BLOCK = 64
part = m.score(*utf8(pa.array([t])))
assert abs(whole[0] - part[0]) < 1e-4
""",
    "op9": """
from winsub.llm import op09_context_tree as op
t = text(24)
def counted(size):
    op.BLOCK = size
    found = {}
    for b in op._counts(iter([pa.RecordBatch.from_arrays([pa.array([t])], ["text"])])):
        for x, n in zip(b.column(1).to_pylist(), b.column(2).to_pylist()):
            if x is not None:
                found[x] = found.get(x, 0) + n
    return found
assert counted(1 << 17) == counted(1 << 20)
""",
}


@pytest.mark.parametrize("name", RUNS)
def test_memory_of_one_long_text(name):
    end = 'print("MB", resource.getrusage(resource.RUSAGE_SELF).ru_maxrss // 1024)'
    done = subprocess.run([sys.executable, "-c", BEGIN + RUNS[name] + end], capture_output=True, text=True, timeout=600)
    assert done.returncode == 0, done.stderr[-2000:]
    assert int(done.stdout.split("MB")[-1]) < MOST_MB
