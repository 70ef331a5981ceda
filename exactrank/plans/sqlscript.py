"""The methods as SQL scripts: session variables carry what the driver would hold."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame

from exactrank.functions.ranks import exact_share


def _named(df: DataFrame, col: str) -> str:
    name = f"quantile_input_{uuid.uuid4().hex[:8]}"
    df.selectExpr(f"{col} AS v").where("v IS NOT NULL").createOrReplaceTempView(name)
    return name


def guided_sql(df: DataFrame, col: str, q: str, accuracy: int = 1000, most: int = 100_000) -> DataFrame:
    """Guided selection in one script: sketch, counts, repair by the top-k that ORDER BY with
    LIMIT and OFFSET becomes. A gap over ``most`` is closed in by sketched bounds on both sides
    first, again and again, so no OFFSET is larger. Returns (q, k, value)."""
    share, spark = exact_share(q), df.sparkSession
    view = _named(df, col)
    kind = spark.table(view).schema["v"].dataType.simpleString()
    inside = f"{view} WHERE (lo IS NULL OR v > lo) AND (hi IS NULL OR v < hi)"
    try:
        out = spark.sql(f"""
BEGIN
  DECLARE n BIGINT; DECLARE k BIGINT; DECLARE rk BIGINT; DECLARE m BIGINT; DECLARE below BIGINT; DECLARE eq BIGINT; DECLARE d INT; DECLARE turn INT = 0; DECLARE done BOOLEAN = false;
  DECLARE p {kind}; DECLARE ans {kind}; DECLARE lo {kind}; DECLARE hi {kind}; DECLARE a {kind}; DECLARE b {kind}; DECLARE s1 DOUBLE; DECLARE s2 DOUBLE; DECLARE s3 DOUBLE;
  DECLARE upto BIGINT; DECLARE over BIGINT; DECLARE eqa BIGINT; DECLARE eqb BIGINT;
  SET n = (SELECT count(v) FROM {view});
  SET k = greatest(1, CAST(ceil(CAST(n AS DECIMAL(38,0)) * {share.numerator} / {share.denominator}) AS BIGINT)) - 1;
  SET rk = k; SET m = n;
  IF n = 0 THEN SET done = true; END IF;
  WHILE NOT done DO
    SET turn = turn + 1;
    SET s2 = (rk + 0.5D) / m; SET s1 = greatest(0D, s2 - {2 / accuracy!r}D); SET s3 = least(1D, s2 + {2 / accuracy!r}D);
    SET (a, p, b) = (SELECT percentile_approx(v, s1, {accuracy}), percentile_approx(v, s2, {accuracy}), percentile_approx(v, s3, {accuracy}) FROM {inside});
    SET (below, eq, upto, eqa, over, eqb) = (SELECT count_if(v < p), count_if(v = p), count_if(v < a), count_if(v = a), count_if(v > b), count_if(v = b) FROM {inside});
    IF rk >= below AND rk < below + eq THEN
      SET ans = p; SET done = true;
    ELSEIF rk >= below + eq AND rk - below - eq <= {most} THEN
      SET d = CAST(rk - below - eq AS INT);
      SET ans = (SELECT v FROM {inside} AND v > p ORDER BY v LIMIT 1 OFFSET d); SET done = true;
    ELSEIF rk < below AND below - rk - 1 <= {most} THEN
      SET d = CAST(below - rk - 1 AS INT);
      SET ans = (SELECT v FROM {inside} AND v < p ORDER BY v DESC LIMIT 1 OFFSET d); SET done = true;
    ELSE
      IF rk >= upto AND rk < upto + eqa THEN SET ans = a; SET done = true;
      ELSEIF rk >= m - over - eqb AND rk < m - over THEN SET ans = b; SET done = true;
      ELSE
        -- The pivot is a bound too, so every turn leaves fewer values.
        IF rk >= below + eq THEN
          IF rk < m - over - eqb THEN SET hi = b; SET m = m - over - eqb; END IF;
          SET lo = p; SET rk = rk - below - eq; SET m = m - below - eq;
        ELSE
          SET hi = p; SET m = below;
          IF rk >= upto + eqa THEN SET lo = a; SET rk = rk - upto - eqa; SET m = m - upto - eqa; END IF;
        END IF;
      END IF;
    END IF;
  END WHILE;
  SELECT CAST({float(share)!r} AS DOUBLE) AS q, k, ans AS value, turn;
END""")
        found = out.select("q", "k", "value")
        return spark.createDataFrame(found.collect(), found.schema)
    finally:
        spark.catalog.dropTempView(view)


def prune_sql(df: DataFrame, col: str, q: str) -> DataFrame:
    """Count and discard as a WHILE loop; the next pivot is the value of greatest hash on its side."""
    share, spark = exact_share(q), df.sparkSession
    view = _named(df, col)
    kind = spark.table(view).schema["v"].dataType.simpleString()
    try:
        out = spark.sql(f"""
BEGIN
  DECLARE n BIGINT; DECLARE k BIGINT; DECLARE rk BIGINT; DECLARE below BIGINT; DECLARE eq BIGINT; DECLARE turn INT = 0; DECLARE done BOOLEAN = false;
  DECLARE p {kind}; DECLARE lo {kind}; DECLARE hi {kind}; DECLARE nlo {kind}; DECLARE nhi {kind};
  SET (n, p, lo, hi) = (SELECT count(v), max_by(v, xxhash64(v)), min(v), max(v) FROM {view});
  SET k = greatest(1, CAST(ceil(CAST(n AS DECIMAL(38,0)) * {share.numerator} / {share.denominator}) AS BIGINT)) - 1;
  SET rk = k;
  WHILE NOT done AND turn < 300 DO
    SET turn = turn + 1;
    SET (below, eq, nlo, nhi) = (SELECT count_if(v < p), count_if(v = p), max_by(CASE WHEN v < p THEN v END, CASE WHEN v < p THEN xxhash64(v, turn) END),
      max_by(CASE WHEN v > p THEN v END, CASE WHEN v > p THEN xxhash64(v, turn) END) FROM {view} WHERE v >= lo AND v <= hi);
    IF rk >= below AND rk < below + eq THEN
      SET done = true;
    ELSEIF rk < below THEN
      SET hi = (SELECT max(v) FROM {view} WHERE v < p);
      SET p = nlo;
    ELSE
      SET rk = rk - below - eq;
      SET lo = (SELECT min(v) FROM {view} WHERE v > p);
      SET p = nhi;
    END IF;
  END WHILE;
  SELECT CAST({float(share)!r} AS DOUBLE) AS q, k, p AS value, done OR n = 0 AS found;
END""")
        rows = out.collect()
        if not rows[0]["found"]:
            raise RuntimeError("rank not found in 300 turns")
        return spark.createDataFrame([tuple(r)[:3] for r in rows], out.select("q", "k", "value").schema)
    finally:
        spark.catalog.dropTempView(view)
