"""Inputs: the given tables, region trees and the experiment workloads."""
