"""Workers of the pipeline's maps, which Spark keeps for later stages, give back what a task has freed."""

import subprocess
import sys

from carrierpath.llm import byte_bpe, links, ngram_join, toxicity

_TASK = """
import sys, numpy as np, pyarrow as pa
from carrierpath.functions.memory import trimmed
kept = []
def run(batches):
    for _ in batches:
        np.ones(30 << 20, dtype=np.uint8)  # from now on glibc takes blocks of this size from its heap
        held = [(np.ones(1 << 20, dtype=np.uint8), kept.append(np.ones(300, dtype=np.uint8))) for _ in range(150)]
        yield len(held)
list((trimmed(run) if sys.argv[1] == "trimmed" else run)([1, 2]))
print(int(next(x for x in open("/proc/self/status") if x.startswith("VmRSS")).split()[1]) // 1024)
"""


def test_a_worker_keeps_no_freed_memory():
    plain, trimmed = (int(subprocess.run([sys.executable, "-c", _TASK, how], capture_output=True, text=True, check=True).stdout) for how in ("plain", "trimmed"))
    assert trimmed < plain - 75


def test_all_maps_of_the_pipeline_are_trimmed():
    for module in (byte_bpe, links, ngram_join, toxicity):
        with open(module.__file__) as f:
            text = f.read()
        assert text.count(".mapInArrow(") == text.count(".mapInArrow(trimmed(") > 0
