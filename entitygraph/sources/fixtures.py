"""Derived record sets with a planted truth, as SQL that Spark and DuckDB both read; see FIXTURES.md."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

#: Twenty syllables, three characters each (fixed values).
SYLLABLES = "BA CO DELFRIGUNHARJO KELLIMMORNESOSTPRAQUIROSSUNTAVULMVERWYN"
RATES = {"good": 8, "moderate": 20, "poor": 45}


@dataclass(frozen=True)
class Sample:
    name: str
    quality: str
    layout: str
    rows: int | None
    kind: str = "person"
    seed: int = 0


SAMPLES = {
    s.name: s
    for s in (
        Sample("S1", "good", "standard", 50), Sample("S2", "good", "standard", 100), Sample("S3", "moderate", "standard", 868, "business"),
        Sample("S4", "good", "standard", 1912), Sample("S5", "good", "standard", 3004), Sample("S6", "moderate", "standard", 19998),
        Sample("S7", "good", "mixed", 2912), Sample("S8", "poor", "standard", 1000), Sample("S9", "poor", "standard", 1000, seed=1),
        Sample("S10", "poor", "mixed", 2000), Sample("S11", "poor", "mixed", 3999), Sample("S12", "poor", "mixed", 6000),
        Sample("S13", "good", "mixed", 2000), Sample("S14", "good", "mixed", 5000), Sample("S15", "good", "mixed", 10000),
        Sample("S16", "poor", "mixed", 2000, seed=1), Sample("S17", "poor", "mixed", 5000), Sample("S18", "poor", "mixed", 10000),
    )
}

#: All customers and all their copies.
WHOLE = Sample("whole", "poor", "standard", None)


def _div(a: str, b: int) -> str:
    return f"CAST(floor(({a}) / {b}) AS BIGINT)"


def word_sql(x: str, n: int) -> str:
    """n syllables, the base-20 digits of x, least digit first."""
    digit = lambda i: f"({_div(x, 20**i)}) % 20" if i else f"({x}) % 20"
    return " || ".join(f"trim(substr('{SYLLABLES}', CAST(1 + 3 * ({digit(i)}) AS INT), 3))" for i in range(n))


def references_sql(sample: Sample) -> str:
    """record_id, truth_id, body of a sample: entities, their copies, damaged fields, one of four layouts, the first rows by record_id (all where rows is None)."""
    rate = RATES[sample.quality]
    hit = lambda p: f"((1009 * (k + 1) + 9176 * (j + 1) + {31337 * p + 65537 * sample.seed}) * 48271 % 2147483647) % 100 < {rate}"
    last = "" if sample.rows is None else f"\n    ORDER BY record_id LIMIT {sample.rows}"
    if sample.kind == "business":
        base = f"""SELECT s_suppkey AS k, s_nationkey AS nation, s_suppkey AS hh,
            upper(p_name) || ' ' || upper(replace(p_brand, '#', '')) AS given, {word_sql('97 * s_suppkey % 8000', 3)} AS family
            FROM (SELECT s.*, n_parts FROM supplier s CROSS JOIN (SELECT count(*) AS n_parts FROM part) q) t JOIN part ON p_partkey = 7 * s_suppkey % n_parts"""
    else:
        base = f"""SELECT c_custkey AS k, c_nationkey AS nation, {_div('c_custkey', 2)} AS hh,
            {word_sql('13 * (31 * c_custkey + 7) % 400', 2)} AS given, {word_sql('(7577 * c_custkey + 3) % 8000', 3)} AS family
            FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey"""
    parts = {
        "name": "given_e || family_e",
        "address": "street_no_e || ' ' || street_e || ' ST NATION' || CAST(nation AS VARCHAR(9)) || zip_e",
        "ssn": "ssn_e",
        "phone": "phone_e",
        "card": "CAST(4000000000000000 + k * 48272144813 % 999999999989 AS VARCHAR(20))",
    }
    row = lambda *names: " || ' ' || ".join(parts[n] for n in names)
    standard = row("name", "address", "ssn", "phone")
    body = (
        standard
        if sample.layout == "standard"
        else f"""CASE (k + j) % 4 WHEN 0 THEN {standard} WHEN 1 THEN {row('ssn', 'name', 'phone', 'address')}
             WHEN 2 THEN {row('phone', 'card', 'name', 'address')} ELSE {row('address', 'card', 'ssn', 'name')} END"""
    )
    return f"""
    SELECT lpad(CAST(10 * k + j AS VARCHAR(12)), 12, '0') AS record_id, k AS truth_id, trim(regexp_replace({body}, {{SPACES}}, ' '{{ALL}})) AS body
    FROM (
        SELECT k, j, nation,
            CASE WHEN {hit(1)} THEN substr(given, 1, 1) WHEN {hit(2)} THEN substr(given, 1, 1) || given ELSE given END AS given_e,
            CASE WHEN {hit(3)} THEN '' WHEN {hit(4)} THEN ' ' || substr(family, 2) ELSE ' ' || family END AS family_e,
            CASE WHEN {hit(5)} THEN substr(street_no, 1, length(street_no) - 1) ELSE street_no END AS street_no_e,
            CASE WHEN {hit(6)} THEN substr(street, 1, length(street) - 1) || 'X' ELSE street END AS street_e,
            CASE WHEN {hit(7)} THEN '' ELSE ' ' || zip END AS zip_e,
            CASE WHEN {hit(8)} THEN '' WHEN {hit(9)} THEN substr(ssn, 1, 3) || ' ' || substr(ssn, 4, 2) || ' ' || substr(ssn, 6, 4)
                 WHEN {hit(10)} THEN substr(ssn, 1, 8) || '0' ELSE ssn END AS ssn_e,
            CASE WHEN {hit(11)} THEN '' WHEN {hit(12)} THEN substr(phone, 1, 3) || ' ' || substr(phone, 4, 3) || ' ' || substr(phone, 7, 4) ELSE phone END AS phone_e
        FROM (
            SELECT b.*, j,
                CAST(100 + 37 * hh % 9900 AS VARCHAR(9)) AS street_no, {word_sql('131 * hh % 8000', 3)} AS street,
                CAST(10000 + 17 * hh % 20000 AS VARCHAR(9)) AS zip, CAST(100000000 + (382258049 * k + 13) % 899999999 AS VARCHAR(12)) AS ssn,
                CAST(200 + 7 * k % 800 AS VARCHAR(4)) || CAST(200 + 11 * k % 800 AS VARCHAR(4)) || CAST(1000 + 4801 * k % 9000 AS VARCHAR(5)) AS phone
            FROM ({base}) b JOIN (SELECT 0 AS j UNION ALL SELECT 1 UNION ALL SELECT 2 UNION ALL SELECT 3 UNION ALL SELECT 4) c ON j < 1 + 7919 * k % 5
        ) x
    ) y{last}"""


def duckdb_references(sample: Sample) -> str:
    return references_sql(sample).replace("{SPACES}", "' +'").replace("{ALL}", ", 'g'")


def register_tables(spark: SparkSession, sf_dir: str, *names: str) -> None:
    for name in names:
        spark.read.parquet(f"{sf_dir}/{name}.parquet").createOrReplaceTempView(name)


def references(spark: SparkSession, sf_dir: str, sample: Sample | str = "S8") -> DataFrame:
    """record_id, truth_id, body; a sample that asks for more rows than the tables give has all there are."""
    sample = SAMPLES[sample] if isinstance(sample, str) else sample
    register_tables(spark, sf_dir, "customer", "nation", "region", "supplier", "part")
    return spark.sql(references_sql(sample).replace("{SPACES}", "' +'").replace("{ALL}", ""))


#: Six invented references of two people who share an address and a middle name (FIXTURES.md section 4).
WORKED_EXAMPLE = [
    ("X000001", 1, "TORVEN MARIS KELDO 418 BRINEWATER LN OAKUM VALE ZR 55210"),
    ("X000002", 1, "TORVEN MARIS KELDO 418 BRINEWATER LN OAKUM VALE ZR 55210 731 40 1187"),
    ("X000003", 1, "TORVEN MARIS K 418 BRINEWATER LN OAKUM VALE ZR 55210 731 40 1187"),
    ("X000004", 1, "TORVEN MARIS KELDO 418 BRINEWATER LN OAKUM VALE ZR 55210 731401187"),
    ("X000005", 2, "PELLIN MARIS SUNDAY 418 BRINEWATER LN OAKUM VALE ZR 55210 902 66 3054"),
    ("X000006", 2, "PELIN MARIS SUNDAY 418 BRINEWATER LN OAKUM VALE ZR 55210 902 66 3054"),
]


def worked_example(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(WORKED_EXAMPLE, "record_id string, truth_id long, body string")
