"""digitsort.operators"""
