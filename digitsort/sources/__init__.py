"""digitsort.sources"""
