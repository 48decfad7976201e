"""Rule closure of subject-predicate-object triples on Spark DataFrames."""
