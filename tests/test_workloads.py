"""Workloads run and their measures move as they should."""

import pytest

from corpusbwt.plans import workloads


def test_every_workload_has_a_name():
    assert workloads.NAMES == tuple(f"w{i:02d}" for i in range(1, 21))


@pytest.mark.parametrize("name", ["w09", "w10"])
def test_sweeps(spark, small, name):
    rows = workloads.run(name, spark, small).measures.collect()
    assert len(rows) == 5 and all(r.seconds > 0 and r.symbols > 0 for r in rows)
    if name == "w10":  # wider spacing, smaller counters
        assert [r.bytes for r in rows] == sorted((r.bytes for r in rows), reverse=True)


def test_blocks_sweep_inserts_into_a_growing_transform(spark, small):
    rows = workloads.run("w08", spark, small).measures.collect()
    sizes = [r.bytes for r in rows if r.param.startswith("M=n/16 ") and r.param.endswith("insert")]
    assert sizes == sorted(sizes) and len(sizes) > 8


def test_compared(spark, small):
    out = workloads.run("w20", spark, small)
    assert set(out.outputs) == {"order_flag_strings", "event_type_strings"} and out.measures.count() == 2


def test_builders_are_timed_with_their_memory(spark, small):
    from corpusbwt.plans import catalog

    row = workloads.measured_builder(catalog.names(spark, small), "block_append").first()
    assert row.symbols > 0 and row.seconds > 0 and row.bytes > 1 << 20


def test_index_of_both_alphabets_keeps_its_bound(spark, small):
    from corpusbwt.plans import catalog

    assert all(r.within for r in catalog.memory_bits(spark, small).collect())
