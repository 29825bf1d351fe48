"""polyedge: higher-order sensor-group anomaly detection on Spark DataFrames."""
