"""Relations over rings and everything that runs on Spark: evaluation, maintenance, enumeration, applications."""
