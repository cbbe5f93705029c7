"""Dynamic programs over very large rooted trees and forests, on Spark."""
