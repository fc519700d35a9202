"""Why did it fail? Mines the feature values behind a failure state from structured logs, on Spark."""
