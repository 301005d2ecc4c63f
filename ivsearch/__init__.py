"""PySpark-native nearest-neighbour search over vectors with closed intervals."""
