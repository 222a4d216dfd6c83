"""The driver's contract, and a sample of queries against their SQL."""

import hashlib

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    con.sql("SET TimeZone='UTC'")
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


def text(frame):
    frame = frame[sorted(frame.columns)]
    return sorted(tuple(repr(round(v, 6)) if isinstance(v, float) else str(v) for v in r) for r in frame.itertuples(index=False))


def test_entry(spark):
    assert entry.entry(spark).columns == ["m_o", "m_p", "m_s"]


def test_every_oracle_has_a_query():
    assert not entry.oracle_sql().keys() - entry.queries().keys()


SAMPLE = [
    "g_summary_trade", "g_doc_shared_lines", "g_doc_line_members", "g_vector_similarity", "c_code_full", "c_code_directed", "c_code_decimal", "c_code_bytes", "c_code_edge_aware", "c_code_edge_dims",
    "f_code_strict", "f_code_log", "f_packets_auto", "f_full_degree", "f_nested_balls", "f_shell_degree", "f_shell_packed", "f_directed", "peel_round_log", "peel_edge_aware", "peel_directed",
    "m_tailed", "m_directed_path", "m_disconnected_count", "m_order_min_edge_card", "b_tree_index_match", "b_agreement", "s_sorted_pass_kept", "s_random_pass_kept", "s_live_counts", "s_live_filter",
    "s_join_static", "s_join_streams", "x_order_containment", "x_conversation_codes", "x_lookup", "x_digest_collisions", "w_sparse_fewlabel", "m_run_set", "k_filter_precision", "r_join_asof", "r_agg_cube",
]


@pytest.mark.parametrize("name", SAMPLE)
def test_query_equals_sql(spark, db, name):
    got, want = entry.queries()[name](spark, SF).toPandas(), db.sql(entry.oracle_sql()[name]).df()
    assert text(got) == text(want)


@pytest.mark.parametrize("name", ["s_session", "s_join_static", "s_live_state"])
def test_streams_of_many_rows_stay_off_the_driver(spark, db, name):
    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass", None)
    out = entry.queries()[name](spark, SF)
    assert out.inputFiles()  # a memory table has none
    assert text(out.toPandas()) == text(db.sql(entry.oracle_sql()[name]).df())
    assert spark.conf.get("spark.sql.streaming.stateStore.providerClass", None) == before


def test_widths_are_of_the_degrees_of_users(spark, db):
    from nbrmatch.functions import codes

    got = {r["degree"]: tuple(r)[1:] for r in entry.queries()["c_widths"](spark, SF).collect()}
    degrees = dict(db.sql("SELECT n, count(*) FROM (SELECT count(*) AS n FROM events GROUP BY user_id) GROUP BY 1").fetchall())
    assert got == {n: (users, codes.max_width(n), codes.max_width(n, codes.DECIMAL)) for n, users in degrees.items()}


@pytest.mark.parametrize("name", ["r_udtf_decode", "r_udtf_pattern"])
def test_table_functions_work_on_a_table(spark, db, name):
    got = entry.queries()[name](spark, SF)
    assert any("events" in f or "orders" in f for f in got.inputFiles())
    assert text(got.toPandas()) == text(db.sql(entry.oracle_sql()[name]).df())


@pytest.mark.parametrize("name", ["c_code_edge_aware", "c_decode"])
def test_codes_have_a_row_for_every_vertex_hubs_too(spark, name):
    from nbrmatch.operators import filters
    from nbrmatch.plans import catalogue

    q = catalogue.TRIANGLE if name == "c_decode" else catalogue.RELATIONS
    start = filters.start(catalogue.view(spark, SF, "T"), q).vertices
    got = entry.queries()[name](spark, SF)
    assert {r["vid"] for r in got.select("vid").collect()} == {r["vid"] for r in start.select("vid").collect()}
    assert name != "c_decode" or got.where("not same").isEmpty()


def test_lines_of_many_documents_keep_their_members(spark, tmp_path):
    from nbrmatch.sources import graphs

    rows = [(k, f"common line\nown line {k}", "en", "s") for k in range(60)] + [(60, " common line ", "en", "s"), (61, "nothing shared", "en", "s"), (62, None, "en", "s")]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").write.parquet(f"{tmp_path}/documents.parquet")
    got = graphs.document_line_members(spark, str(tmp_path)).collect()
    assert sorted(r["vid"] - 7 * graphs.SPACE for r in got) == list(range(61)) and len({r["line"] for r in got}) == 1


def test_graph_codes_equal_plain_integers(spark):
    from nbrmatch.functions.codes import ncode

    own = {r["graph_id"]: [int(x) for x in r["codes"].split(",")] for r in entry.queries()["x_conversation_codes"](spark, SF).collect()}
    got = {r["graph_id"]: r for r in entry.queries()["x_conversation_digests"](spark, SF).collect()}
    assert got.keys() == own.keys()
    for g, r in got.items():
        code = ncode(own[g])
        assert r["n_vertices"] == len(own[g]) and r["digits"] == len(str(code))
        assert r["digest"] == hashlib.sha256(code.to_bytes((code.bit_length() + 8) // 8, "big")).hexdigest()
