"""Full-batch graph learning as a Spark engine: cover-routed exchange, quantized messages, training."""
