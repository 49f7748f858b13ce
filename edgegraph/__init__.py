"""Graph analytics over edge partitionings, and operators for training-data pipelines."""
