"""steepdraw: training rows drawn in proportion to how far they would move the model, on Spark."""
