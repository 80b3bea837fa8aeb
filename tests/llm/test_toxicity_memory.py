"""Training of the toxicity model on the driver."""

import subprocess
import sys
from pathlib import Path

import pytest

CODE = """
import resource, numpy as np
from gradvb.llm import toxicity
rng = np.random.default_rng(1)
texts = [" ".join(f"w{k}" for k in rng.integers(0, 30_000, 4000)).encode() for _ in range(160)]
y = (np.arange(len(texts)) % 2).astype(np.int64)
toxicity.fit_toxicity(texts[:4], y[:4])
before = resource.getrusage(resource.RUSAGE_SELF).ru_maxrss
toxicity.fit_toxicity(texts, y)
print((resource.getrusage(resource.RUSAGE_SELF).ru_maxrss - before) / 1024)
"""


@pytest.mark.skipif(sys.platform != "linux", reason="ru_maxrss is in kB on Linux")
def test_training_takes_little_memory_beside_its_texts():
    run = subprocess.run([sys.executable, "-c", CODE], capture_output=True, text=True, check=True, cwd=Path(__file__).resolve().parents[2])
    assert float(run.stdout) < 90
