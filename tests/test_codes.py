"""Codes: known values, the bijection, and that columns agree with plain integers."""

import itertools
import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from nbrmatch.functions import codes, udfs
from nbrmatch.operators.pattern import Pattern, parse

WORKED = parse("(u1:A)-(u2:B), (u1)-(u3:B), (u2)-(u3), (u3)-(u4:C), (u3)-(u5:D)")


def test_known_codes():
    assert codes.ncode([0, 2, 0, 0]) == 12
    assert codes.ncode([1, 1, 0, 0]) == 13
    assert codes.ncode([1, 1, 1, 1]) == 49
    assert codes.ncode([0, 1, 0, 0]) == 3
    assert codes.ncode([0, 1, 0, 1]) == 7
    assert codes.ncode([12, 7]) == 202
    assert codes.ncode([12, 1, 3]) == 919
    assert codes.ncode([0, 2, 1, 1]) == 48
    assert codes.ncode([0, 0, 1, 1]) == 6


def test_worked_pattern():
    assert [WORKED.code(u) for u in ("u1", "u2", "u3", "u4", "u5")] == [12, 13, 49, 3, 3]
    assert [codes.ncode(WORKED.ball(u, 2)) for u in ("u1", "u2", "u3", "u4", "u5")] == [48, 49, 49, 52, 62]
    assert [codes.ncode(WORKED.ball(u, 2, exactly=True)) for u in ("u1", "u2", "u3", "u4", "u5")] == [6, 6, 0, 23, 29]


def test_bijection_and_bands():
    for k in range(1, 5):
        seen = {}
        for x in itertools.product(range(6), repeat=k):
            if sum(x) <= 5:
                seen[codes.ncode(x)] = x
                low, high = codes.band(sum(x), k)
                assert low <= codes.ncode(x) <= high
        assert sorted(seen) == list(range(len(seen)))


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(0, 60), min_size=1, max_size=9), st.data())
def test_decode_bump_drop(x, data):
    c = codes.ncode(x)
    assert codes.decode(c, len(x)) == x
    rank = data.draw(st.integers(1, len(x)))
    more = [n + (k == rank - 1) for k, n in enumerate(x)]
    assert codes.bump(c, x, rank) == codes.ncode(more)
    assert codes.drop(codes.ncode(more), more, rank) == c


@given(st.integers(0, 10**12), st.integers(0, 10**12))
def test_pairing(a, b):
    assert codes.unpair(codes.pair(a, b)) == (a, b)
    assert codes.ncode([b, a]) in (codes.pair(a, b), codes.pair(b, a))


def test_step_forms_agree():
    for p in range(0, 20):
        for s in range(0, 40):
            assert codes.step_interleaved(p, s) == codes.step(p, s) == codes.step_factorial(p, s)


def test_nesting_shapes():
    values = [3, 1, 4, 1]
    assert codes.pair_nested(values) == codes.pair(codes.pair(3, 1), codes.pair(4, 1))
    assert codes.pair_nested(values, "left") == codes.pair(codes.pair(codes.pair(3, 1), 4), 1)
    assert codes.pair_nested(values, "balanced") < codes.pair_nested(values, "left")


def test_widths():
    assert [codes.max_width(n) for n in (50, 100, 1000, 10**4, 10**6, 10**9)] == [23, 15, 7, 5, 3, 2]
    assert [codes.max_width(n, codes.DECIMAL) for n in (50, 100, 1000)] == [87, 45, 17]


def test_logs_collide_where_codes_do_not():
    x = [0] * 19 + [100]
    c = codes.ncode(x)
    y = codes.decode(c + 1, 20)
    assert codes.log_code(x) == codes.log_code(y) and x != y
    assert codes.log_code([0, 0]) == 0.0


def test_columns(spark):
    rng = random.Random(1)
    rows = [[rng.randint(0, 12) for _ in range(5)] for _ in range(60)] + [[0] * 5]
    df = spark.createDataFrame(rows, ", ".join(f"x{k} long" for k in range(1, 6)))
    x = [F.col(f"x{k}") for k in range(1, 6)]
    got = df.select(
        *x, codes.ncode_column(x).alias("c"), codes.ncode_column(x, 10).alias("capped"), codes.ncode_array(F.array(*x)).alias("a"), codes.ncode_decimal(x).alias("d"),
        codes.ncode_bytes(F.array(*x)).alias("b"), codes.ncode_log(x).alias("log"), codes.packet_columns(x, 2).alias("p"), codes.bump_column(codes.ncode_column(x), x, 2).alias("bumped"),
        codes.drop_column(codes.bump_column(codes.ncode_column(x), x, 2), [x[0], x[1] + 1, *x[2:]], 2).alias("dropped"),
        udfs.decode_column(5)(codes.ncode_column(x)).alias("v"),
    ).collect()
    for r in got:
        v = [r[f"x{k}"] for k in range(1, 6)]
        c = codes.ncode(v)
        assert r["c"] == r["a"] == int(r["d"]) == int.from_bytes(r["b"], "big") == c
        assert r["capped"] == (c if sum(v) <= 10 else None)
        assert r["log"] == pytest.approx(codes.log_code(v), abs=1e-9)
        assert list(r["p"]) == codes.packets(v, 2)
        assert r["bumped"] == codes.bump(c, v, 2)
        assert r["dropped"] == c
        assert list(r["v"]) == v


def test_many_labels_use_the_fold(spark):
    df = spark.range(1).select(*(F.lit(1 if k < 3 else 0).cast("long").alias(f"x{k}") for k in range(20)))
    x = [F.col(f"x{k}") for k in range(20)]
    assert df.select(codes.ncode_column(x, 5).alias("c")).first()["c"] == codes.ncode([1, 1, 1] + [0] * 17)


def test_pattern_text():
    q = parse("(a:C:BUILDING)-[placed]-(b:O:1-URGENT), (b)-(c:P)")
    assert q.vertices == {"a": "C:BUILDING", "b": "O:1-URGENT", "c": "P"} and q.edges == (("a", "b", "placed"), ("b", "c", None)) and not q.directed
    d = parse("(a:X)<-[e]-(b:Y)->(c:X)")
    assert d.directed and d.edges == (("b", "a", "e"), ("b", "c", None))
    with pytest.raises(ValueError):
        parse("(a)-(b:X)")
    with pytest.raises(ValueError):
        Pattern({"a": "X"}, (("a", "a", None),))


def test_automorphisms_and_core():
    assert len(parse("(a:X)-(b:X)").automorphisms()) == 2
    assert len(parse("(a:X)-(b:X), (b)-(c:X), (a)-(c)").automorphisms()) == 6
    assert WORKED.core() == ["u1", "u2", "u3"]


def test_decimals_and_bytes_of_large_sums(spark):
    rows = [[n, n // 2, 3, n, 1] for n in (0, 63, 64, 65, 1000, 10**5)]
    df = spark.createDataFrame(rows, ", ".join(f"x{k} long" for k in range(1, 6)))
    x = [F.col(f"x{k}") for k in range(1, 6)]
    width = codes.bytes_width(3 * 10**5, 5)
    for r in df.select(*x, codes.ncode_decimal(x).alias("d"), codes.ncode_bytes(F.array(*x), width).alias("b")).collect():
        c = codes.ncode(list(r)[:5])
        assert int(r["d"]) == int.from_bytes(r["b"], "big") == c


def test_edge_dims(spark):
    df = spark.createDataFrame([(1, 2, 3, 4)], "x1 long, x2 long, e1 long, e2 long")
    x, e = [F.col("x1"), F.col("x2")], [F.col("e1"), F.col("e2")]
    got = df.select(codes.edge_dims(x, e).alias("a"), codes.edge_dims(x, e[:1], "shared").alias("b")).first()
    assert list(got["a"]) == [1, 2, 3, 4] and list(got["b"]) == [4, 2]
