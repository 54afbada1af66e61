"""Station identity on Spark: candidate pairs, similarity measures, forests and their evaluation."""
