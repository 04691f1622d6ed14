"""Block sketching and coded descent for tall least squares on Spark."""
