"""Evaluation of predictive models by lossless compression over calendar time, on Spark."""
