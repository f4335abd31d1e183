"""Spark-native learning over joined relations: moment matrices, trees and rewrites that never store the join."""
