"""fragmap: log-evidence keyword mapping and join inference on Spark."""
