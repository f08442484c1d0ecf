"""Evidence from files and databases, programs from text files, and sinks for fields and worlds."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ruleworld.plans.ground import Atoms, Field
from ruleworld.plans.program import Predicate, Program

FORMATS = ("parquet", "csv", "json", "orc")


def schema_of(p: Predicate) -> str:
    """Columns of a relation's evidence: its arguments, and ``truth`` where it is open."""
    cols = [f"{c} {kind}" for c, (_, kind) in zip(p.columns, p.args, strict=True)]
    return ", ".join(cols + (["truth tinyint"] if p.open else []))


def read_evidence(spark: SparkSession, p: Predicate, path: str, kind: str = "parquet", **options) -> DataFrame:
    """Evidence of one relation. Text formats take the declared schema; a malformed line is an error, not a null row."""
    if kind not in FORMATS:
        raise ValueError(f"unknown format {kind!r}, known are {', '.join(FORMATS)}")
    reader = spark.read.format(kind).options(**options)
    if kind in ("csv", "json"):
        reader = reader.schema(schema_of(p)).option("mode", "FAILFAST")
    return reader.load(path)


def read_jdbc(spark: SparkSession, url: str, relation: str, column: str, lower: int, upper: int, parts: int, **properties) -> DataFrame:
    """Evidence from a database table, read in ranges of a numeric column by ``parts`` tasks."""
    return spark.read.jdbc(url, relation, column=column, lowerBound=lower, upperBound=upper, numPartitions=parts, properties=properties)


def read_program(spark: SparkSession, path: str) -> Program:
    """A program from a text file of any file system that the session reads."""
    lines = spark.read.text(path, wholetext=True).collect()
    return Program.parse("\n".join(r.value for r in lines))


def write_field(fld: Field, path: str) -> None:
    """Clauses by rule and atoms by predicate; an earlier run's folder is replaced."""
    fld.clauses.repartitionByRange("rule", "cid").sortWithinPartitions("rule", "cid").write.mode("overwrite").partitionBy("rule").parquet(f"{path}/clauses")
    fld.constants.write.mode("overwrite").parquet(f"{path}/constants")
    for name, t in fld.atoms.tables.items():
        t.write.mode("overwrite").parquet(f"{path}/atoms/{name}")


def read_field(spark: SparkSession, program: Program, path: str) -> Field:
    clauses = spark.read.parquet(f"{path}/clauses").select("cid", F.col("rule").cast("string").alias("rule"), "lits", "weight", "is_hard", "multiplicity")
    tables = {name: spark.read.parquet(f"{path}/atoms/{name}") for name in program.predicates}
    return Field(Atoms(program, tables), clauses, spark.read.parquet(f"{path}/constants"))


def write_world(fld: Field, world: DataFrame, path: str, value: str = "value") -> None:
    """A world (``value``) or marginals (``p``) with the atoms' arguments as text, partitioned by predicate."""
    rows = fld.atoms.open_rows().join(world.select("aid", value), "aid", "left")
    rows.select("pred", "aid", "args", "truth", value).write.mode("overwrite").partitionBy("pred").parquet(path)
