"""claimloom: build and audit model-written encyclopedias with Spark DataFrames."""
