"""Cases of the second review for the text operators: each failed before its finding was settled."""

import random
import re
import subprocess
import sys
from functools import partial
from pathlib import Path

import public_tokenizers as P
import pyarrow as pa

from polyedge.llm import common, packing, queries, secrets, token_counts, webp


def test_token_counts_shuffle_no_text(spark, sf, monkeypatch):
    """Also where the ids to recount are too many to be broadcast."""
    plans, commit = [], token_counts.Rollup.commit

    def spy(self, batch_id, deltas):
        plans.append(deltas._sc._jvm.PythonSQLUtils.explainString(deltas._jdf.queryExecution(), "formatted"))
        return commit(self, batch_id, deltas)

    monkeypatch.setattr(token_counts.Rollup, "commit", spy)
    held = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    try:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        queries.op9_token_counts(spark, sf).collect()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", held)
    moved = [b for p in plans for b in re.findall(r"^\(\d+\) Exchange\nInput \[\d+\]: (.*)$", p, re.M)]
    assert len(moved) > 2 and not any("text#" in b for b in moved)


def test_a_worker_keeps_no_memo_of_another_operator():
    """Stages of the pipeline meet in the same workers; before, the packer's memos stayed for all of them."""
    batch = pa.RecordBatch.from_arrays([pa.array([1, 2]), pa.array(["one two three", None])], names=["doc_id", "text"])
    list(packing._pieces(iter([batch]), P.path("byte_bpe_50k.json"), 2048, 0, False))
    assert packing.encoder.cache_info().currsize == 1
    redact = partial(secrets._redacted, model=secrets.default_model())
    made = list(common._run(iter([batch]), redact, 1, 1, [pa.string(), pa.int64()], ["doc_id", "redacted_text", "n_secrets"]))
    assert made[0].column(1).to_pylist() == ["one two three", ""]
    assert packing.encoder.cache_info().currsize == 0


def test_packing_memos_are_bounded_and_frequent_chunks_stay(monkeypatch):
    """Two workers and a JVM share an executor: half the memo is young, and what is met again comes back from the old half."""
    assert packing.MEMO_BYTES + packing.KNOWN_BYTES <= 120 << 20
    monkeypatch.setattr(packing, "MEMO_BYTES", 40_000)
    encode = packing.DocumentEncoder(P.path("byte_bpe_50k.json"))
    texts = [" ".join(["often, seen", *(f"w{i}x{k}" for k in range(40)), "Often! seen."]) for i in range(60)] * 2
    for at in range(0, len(texts), 4):
        part = texts[at : at + 4]
        assert encode(part) == [encode._encode(t).tobytes() for t in part]
        assert len(encode.memo) + len(encode.old) < 600 and (at < 40 or "seen" in encode.memo)


def test_media_reuse_freed_arrays():
    """Pages touched for the first time, after a first round: arrays of each text were given back and mapped anew."""
    code = "import resource, random; from polyedge.llm import webp; random.seed(1); t = [' '.join(random.choices([f'w{i}' for i in range(900)], k=3000)) for _ in range(40)]; webp._digested(t); a = resource.getrusage(0).ru_minflt; webp._digested(t); print(resource.getrusage(0).ru_minflt - a)"
    faults = int(subprocess.run([sys.executable, "-c", code], cwd=Path(__file__).parents[2], capture_output=True, text=True, check=True).stdout)
    assert faults < 40 * 50


def test_a_text_takes_few_calls_to_store_and_read():
    """Calls for a text of 3.3 kB, whose fixed share weighs most: 2,150 before, 1,450 after."""
    rng = random.Random(1)
    words = ["".join(rng.choices("abcdefghijklmnopqrstuvwxyz", k=rng.randint(2, 9))) for _ in range(200)]
    texts = [" ".join(rng.choices(words, k=500)) for _ in range(20)]
    webp._digested(texts)
    calls = 0

    def count(frame, event, arg):
        nonlocal calls
        calls += event in ("call", "c_call")

    held = sys.getprofile()
    sys.setprofile(count)
    try:
        webp._digested(texts)
    finally:
        sys.setprofile(held)
    assert calls < 1800 * len(texts)
