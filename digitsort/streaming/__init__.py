"""digitsort.streaming"""
