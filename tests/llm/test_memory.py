"""What the kernels leave behind in a Python worker."""

import os
import subprocess
import sys

ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
CODE = """
import re
import numpy as np
from gridlake.llm.common import doc_chunks
from gridlake.llm.substring_dedup import all_anchors


def held():
    return int(re.search(r"VmHWM:\\\\s+(\\\\d+)", open("/proc/self/status").read())[1]) / 1024


data = np.random.default_rng(1).integers(97, 123, 8 << 20, dtype=np.uint8)
offs = np.arange(0, len(data) + 1, 2048)
before = held()
found = sum(len(all_anchors(data, offs[lo : hi + 1])[1]) for lo, hi in doc_chunks(offs))
print(found, held() - before)
"""


def test_anchors_of_many_texts_take_little_memory():
    """The kernel's arrays follow its chunks: with chunks of 1 MB they took over 100 MB."""
    said = subprocess.run([sys.executable, "-c", CODE.replace("\\\\", "\\")], capture_output=True, text=True, check=True, env=os.environ | {"PYTHONPATH": ROOT}).stdout.split()
    assert int(said[0]) > 100_000 and float(said[1]) < 60
