"""Operators over corpora, moments, trees and phrases."""
