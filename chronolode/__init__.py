"""Top-k high-utility episode mining over one long event sequence, on Spark."""
