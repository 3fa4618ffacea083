"""chaincores: group linkage of records on Spark."""
