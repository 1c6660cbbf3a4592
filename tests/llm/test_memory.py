"""What a worker process holds: batches bounded by bytes, and nothing that no task uses."""

from pathlib import Path

import pyarrow as pa

from widefeat.llm.common import ARROW_BYTES, ship, text_slices


def test_texts_come_in_small_batches(spark):
    docs = spark.range(0, 4000, 1, 1).selectExpr("id as doc_id", "repeat(cast(id % 10 as string), 5000) as text")
    ship(spark)

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows]), pa.array([b.nbytes])], ["n", "size"])

    got = docs.mapInArrow(run, "n long, size long").collect()
    assert sum(r.n for r in got) == 4000 and max(r.size for r in got) < 2 * ARROW_BYTES


def test_memory_goes_back():
    rss = lambda: int(Path("/proc/self/statm").read_text().split()[1]) * 4096
    held = [bytes(1000) for _ in range(300_000)]
    last = held[-1]  # the heap's end stays in use
    full = rss()
    del held
    b = pa.RecordBatch.from_arrays([pa.array(["a b", None, "c"])], ["text"])
    assert sum(p.num_rows for p in text_slices(b)) == 3
    assert full - rss() > 150_000_000 and len(last) == 1000
