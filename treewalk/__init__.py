"""Random spanning trees and random walks on Spark."""
