"""Cost of removing repeats by broadcast automata of all documents: python tests/llm/broadcast_form.py SF_DIR.

Shards follow the order of ids. Inside a shard the automaton grows with the text; every later document
streams through it. Prints words, shards, words removed and core seconds; works in plain processes.
"""

import sys
import time
from concurrent.futures import ProcessPoolExecutor
from pathlib import Path

import duckdb
import numpy as np

sys.path.insert(0, str(Path(__file__).resolve().parents[2]))
from rangeknn.llm.substring import LENGTH, SuffixAutomaton, covered

SHARD_WORDS = 200_000


def shard_windows(job):
    """(document, window) pairs that one shard shows to be repeats, and seconds to build and to stream."""
    texts, first, last = job
    automaton, found, began = SuffixAutomaton(), [], time.process_time()
    for d in range(first, last):
        found += [(d, e + 1 - LENGTH) for e, w in enumerate(texts[d]) if automaton.add(w) >= LENGTH]
        automaton.end_text()
    built = time.process_time()
    for d in range(last, len(texts)):
        found += [(d, e + 1 - LENGTH) for e, n in enumerate(automaton.statistics(texts[d])) if n >= LENGTH]
    return found, built - began, time.process_time() - built


def main(sf_dir: str) -> None:
    source = sf_dir + "/documents.parquet"
    source += "/*.parquet" if Path(source).is_dir() else ""
    texts = [(t or "").encode().split() for (t,) in duckdb.sql(f"SELECT text FROM '{source}' ORDER BY doc_id").fetchall()]
    at = np.cumsum([0, *map(len, texts)]) // SHARD_WORDS
    cuts = [*np.flatnonzero(np.diff(at, prepend=-1)).tolist(), len(texts)]
    jobs = [(texts, a, b) for a, b in zip(cuts[:-1], cuts[1:], strict=True) if a < b]
    starts = [[] for _ in texts]
    build = stream = 0.0
    with ProcessPoolExecutor(8) as pool:
        for found, b, s in pool.map(shard_windows, jobs):
            build, stream = build + b, stream + s
            for d, w in found:
                starts[d].append(w)
    removed = sum(int(covered(np.array(w), np.array(w) + LENGTH, len(t)).sum()) for w, t in zip(starts, texts, strict=True) if w)
    print(f"{sum(map(len, texts))} words, {len(jobs)} shards, {removed} words removed, {build:.1f} s build, {stream:.1f} s stream")


if __name__ == "__main__":
    main(sys.argv[1])
