"""Searches, trees and features: control on the driver, counts on the cluster."""
