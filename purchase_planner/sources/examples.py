"""Small literal instances: worked cases for tests and demonstrations."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..functions import measures as M
from ..functions.measures import FD

# The worked instances, as given. Age groups are labels of our own.
FD_FIVE = [("t1", "a1", "b1"), ("t2", "a1", "b1"), ("t3", "a1", "b2"), ("t4", "a1", "b3"), ("t5", "a2", "b2")]
DIRT_LEFT = [("a1", "b1", f"c{i + 3}") for i in range(1, 997)] + [("a1", "b2", "c1"), ("a1", "b2", "c2"), ("a1", "b3", "c3"), ("a1", "b3", "c3")]
DIRT_RIGHT = [("c1", "d1", "e1"), ("c1", "d1", "e1"), ("c2", "d1", "e2"), ("c3", "d1", "e2"), ("c4", "d1", "e2")]
DIRT_JOIN_PRINTED = [("a1", "b2", "c1", "d1", "e1"), ("a1", "b2", "c1", "d1", "e1"), ("a1", "b2", "c2", "d1", "e2"), ("a1", "b3", "c3", "d1", "e2"), ("a1", "b3", "c3", "d1", "e2")]
OPTIONS = {
    "ds": ("age string, zipcode string, population long", [("g1", "10003", 7000), ("g2", "01002", 3500), ("g3", "07003", 1200), ("g4", "07003", 5800), ("g5", "07304", 2000)]),
    "d1": ("zipcode string, state string", [("07003", "NJ"), ("07304", "NJ"), ("10001", "NY"), ("10001", "NJ")]),
    "d2": ("state string, disease string, cases long", [("MA", "Flu", 300), ("NJ", "Flu", 400), ("Florida", "Lyme disease", 130), ("California", "Lyme disease", 40), ("NJ", "Lyme disease", 200)]),
    "d3": ("gender string, race string, disease string, cases long", [("M", "White", "Flu", 200), ("F", "Asian", "AIDS", 30), ("M", "White", "Diabetes", 4000), ("M", "Hispanic", "Flu", 140)]),
    "d4": ("age string, gender string, race string, population long", [("g1", "M", "White", 400000), ("g2", "F", "Asian", 100000), ("g3", "M", "White", 300000), ("g4", "M", "Hispanic", 50000)]),
    "d5": ("age string, address string, insurance string, disease string", [("g1", "10 North St.", "UnitedHealthCare", "Flu"), ("g2", "5 Main St.", "MedLife", "HIV"), ("g3", "25 South St.", "UnitedHealthCare", "Flu")]),
}


def frame(spark: SparkSession, name: str) -> DataFrame:
    if name in OPTIONS:
        schema, rows = OPTIONS[name]
        return spark.createDataFrame(rows, schema)
    rows, columns = {"fd_five": (FD_FIVE, "tid a b"), "dirt_left": (DIRT_LEFT, "a b c"), "dirt_right": (DIRT_RIGHT, "c d e"), "dirt_join_printed": (DIRT_JOIN_PRINTED, "a b c d e")}[name]
    return spark.createDataFrame(rows, columns.split())


def worked_qualities(spark: SparkSession) -> DataFrame:
    """Qualities of the worked instances: good before the join, bad after it."""
    ab, de = FD(("a",), "b"), FD(("d",), "e")
    real = frame(spark, "dirt_left").join(frame(spark, "dirt_right"), "c")
    rows = [
        ("fd_five", M.fd_quality(frame(spark, "fd_five"), ab)),
        ("dirt_left", M.fd_quality(frame(spark, "dirt_left"), ab)),
        ("dirt_right", M.fd_quality(frame(spark, "dirt_right"), de)),
        ("dirt_join_printed", M.joint_quality(frame(spark, "dirt_join_printed"), [ab, de])),
        ("dirt_join_real", M.joint_quality(real, [ab, de])),
    ]
    return spark.createDataFrame(rows, "example string, quality double")


def purchase_options(spark: SparkSession, own: DataFrame, paths: dict[str, list[tuple[DataFrame, list[str]]]], have: str, want: str) -> DataFrame:
    """Each purchase option, with and without the shopper's own table: summed informativeness, join size, correlation of two attributes.

    An option is a path of tables with the attributes that each is joined on, the first with the own table on all in common.
    Without the own table, only options count whose first table holds the attribute that the shopper has.
    """
    rows = []
    for option, path in paths.items():
        for with_own in (False, True):
            if not with_own and have not in path[0][0].columns:
                continue
            steps = [(own, []), *path] if with_own else path
            out, weight, previous = steps[0][0], 0.0, steps[0][0]
            for df, join in steps[1:]:
                join = join or [c for c in previous.columns if c in df.columns]
                weight += M.informativeness(previous, df, join)
                shared = [c for c in df.columns if c in out.columns and c not in join]
                out, previous = out.join(df.drop(*shared), join), df
            rows.append((option, with_own, weight, out.count(), M.correlation(out, [have], [want])))
    return spark.createDataFrame(rows, "option string, with_own boolean, ji double, join_rows long, corr double")


def literal_options(spark: SparkSession) -> DataFrame:
    """purchase_options of the worked instances: correlation of age with disease."""
    t = {n: frame(spark, n) for n in OPTIONS}
    paths = {
        "1": [(t["d1"], []), (t["d2"], ["state"])],
        "2": [(t["d4"].select("age", "gender", "population"), []), (t["d3"].select("gender", "disease", "cases"), ["gender"])],
        "3": [(t["d4"].select("age", "race", "population"), []), (t["d3"].select("race", "disease", "cases"), ["race"])],
        "4": [(t["d5"], [])],
        "5": [(t["d4"], []), (t["d3"], ["gender", "race"])],
    }
    return purchase_options(spark, t["ds"].withColumnRenamed("population", "own_population"), paths, "age", "disease")
