"""Collection and analysis of user records under local differential privacy, on Spark."""
