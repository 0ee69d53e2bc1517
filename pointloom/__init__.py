"""pointloom: Spark-native point-cloud lifting, voxel tokenising and masked pre-training, with corpus operators in ``llm``."""
