"""Value types and functions over patterns; no Spark session is needed here."""
