"""softlanes: many linear systems that share one matrix, solved by a deadline on DataFrames."""
