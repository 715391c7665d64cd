"""Every registered query of the map methods against its SQL twin, on the smallest tables."""

import compare
import pytest
from topomap.plans import catalogue

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", sorted(catalogue.oracle_sql()))
def test_twin(spark, name):
    assert compare.mismatch(spark, SF, catalogue.queries()[name], catalogue.oracle_sql()[name]) == ""


@pytest.mark.parametrize("name", sorted(set(catalogue.queries()) - set(catalogue.oracle_sql())))
def test_runs(spark, name):
    assert catalogue.queries()[name](spark, SF).count() > 0


def test_regimes_are_of_a_map_that_uses_its_nodes():
    """The queries' regimes come from trained maps on which several nodes are occupied, so that their twins agree on something."""
    con = compare.connection("/root/testdata/sf0.01")
    for ctes in (catalogue._DOCS_WON, catalogue._CELLS_WON):
        assert con.execute(catalogue.T.with_(*ctes) + "SELECT count(DISTINCT node) FROM won").fetchone()[0] >= 10


def test_entry(spark):
    import __spark_entry__

    rows = __spark_entry__.entry(spark).collect()
    assert sum(r["n"] for r in rows) == 193 and abs(sum(r["rfo"] for r in rows) - 1) < 1e-9


def test_reproducible_map_separates_languages(spark):
    """Regimes of a trained map follow the languages better than the largest language alone would, and staggered order costs no accuracy."""
    from topomap.config import MapConfig
    from topomap.functions import measures
    from topomap.operators.baselines import fit_many, variant

    sf = "/root/testdata/sf0.01"
    x = catalogue.docs_v(spark, sf).join(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang"), "doc_id").cache()
    cfg = MapConfig(4, 3, max_passes=40, horizon=40)
    models = fit_many(x, {n: variant(cfg, n) for n in ("standard", "gradient_staggered")}, key=["doc_id"])
    won = {n: m.classify(x) for n, m in models.items()}
    error = {n: measures.quantization_error(w).first()[0] for n, w in won.items()}
    assert measures.purity(won["gradient_staggered"], "lang").first()[0] > 0.75
    assert error["gradient_staggered"] < 1.1 * error["standard"]


def test_decimals_that_end_in_a_half_round_as_in_the_twin(spark):
    """41 / 640 is a little below 0.0640625 and the shortest decimals that tell it are that number."""
    from pyspark.sql import functions as F

    values = [(k, n) for n in (64, 128, 320, 640, 1280, 3200, 6400) for k in range(1, n, 2)]
    x = F.col("k") / F.col("n")
    rows = spark.createDataFrame(values, "k long, n long").select("k", "n", catalogue.r6(x).alias("one"), catalogue.r6_array(F.array(x)).alias("list")).collect()
    told = compare.duckdb.connect().execute("SELECT k, n, round(k::DOUBLE / n, 6) FROM (SELECT v[1] AS k, v[2] AS n FROM (SELECT unnest(?) AS v))", [[list(v) for v in values]]).fetchall()
    assert {(r["k"], r["n"]): (r["one"], r["list"][0]) for r in rows} == {(k, n): (v, v) for k, n, v in told}


def test_grids_of_long_lists_are_those_of_the_twin(spark, monkeypatch):
    """3,600,000 samples ask for 300,000 nodes, more than the twin's sides below 400 give."""
    counts = [("lines", 3_600_000), ("cells", 81_775), ("docs", 1_100_000), ("events", 1_900_000), ("few", 7)]
    monkeypatch.setattr(catalogue, "_counts", lambda spark, sf_dir: spark.createDataFrame(counts, "name string, n long"))
    sql = catalogue.oracle_sql()["grid_from_density_cases"]
    told = "WITH counts AS (SELECT * FROM (VALUES " + ", ".join(map(str, counts)) + ") v(name, n))" + sql[sql.index("SELECT name, n, r.range") :]
    rows = catalogue.queries()["grid_from_density_cases"](spark, SF).collect()
    assert sorted(map(tuple, rows)) == sorted(compare.duckdb.connect().execute(told).fetchall())


@pytest.mark.parametrize("name", ["determinism_fingerprints", "set_ops_runs", "similar_regimes", "relay_equals_fold"])
def test_histograms_are_made_once(spark, monkeypatch, name):
    """Training reads histograms from a table, and a query's maps that are equal are trained once."""
    fits, real = [], catalogue.fit_map
    monkeypatch.setattr(catalogue, "fit_map", lambda df, *a, **k: (fits.append(df.inputFiles()), real(df, *a, **k))[1])
    catalogue.queries()[name](spark, SF)
    assert len(fits) == {"determinism_fingerprints": 4, "relay_equals_fold": 2}.get(name, 1)
    assert all("docs-records" in f for files in fits for f in files)


@pytest.mark.parametrize("name", ["grid_distances_4x3", "influence_table_t0", "influence_table_t20", "init_gradient_4x3_d42", "init_random_hashed", "schedule_radius_rate", "staggered_start_fairness", "staggered_udtf"])
def test_tables_of_a_map_come_from_a_given_list(monkeypatch, name):
    """The query reads the list of nations' months, which is made of lineitem and supplier."""
    class Read(Exception):
        pass

    def stop(*a):
        raise Read

    monkeypatch.setattr(catalogue.workloads, "nations", stop)
    with pytest.raises(Read):
        catalogue.queries()[name](__import__("unittest.mock", fromlist=["MagicMock"]).MagicMock(), SF)


@pytest.mark.parametrize("name", ["train_toy_to_stop", "train_toy_recursive_sql"])
def test_short_lists_come_from_given_tables(spark, tmp_path, name):
    """Other order lines give another map."""
    for t in ("lineitem", "supplier"):
        rows = spark.read.parquet(f"{SF}/{t}.parquet")
        (rows.where("l_suppkey % 3 > 0 or l_quantity > 25") if t == "lineitem" else rows).write.parquet(str(tmp_path / f"{t}.parquet"))
    one, two = (sorted(map(str, catalogue.queries()[name](spark, d).collect())) for d in (SF, str(tmp_path)))
    assert one != two
