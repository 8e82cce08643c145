"""Queries, join trees and the choice of a method."""
