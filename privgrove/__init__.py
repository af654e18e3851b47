"""privgrove: differentially private boosted trees and their surroundings, on Spark DataFrames."""

__version__ = "0.1.0"
